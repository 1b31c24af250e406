"""Ordering, octrees, searches, baselines, locality and cost measures."""
