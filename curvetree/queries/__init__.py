"""Registered queries over the given tables, and their SQL twins for another engine."""

from __future__ import annotations

from . import experiments, relational_ops, searches, structure

MODULES = (structure, searches, relational_ops, experiments)
QUERIES = {name: fn for m in MODULES for name, fn in m.QUERIES.items()}
ORACLE = {name: sql for m in MODULES for name, sql in m.ORACLE.items()}
