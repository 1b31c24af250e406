"""Neighbourhood search on curve-ordered three-dimensional point sets, for Spark."""
