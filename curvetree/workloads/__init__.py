"""The experiments, re-expressed on the given tables. ``python -m curvetree.workloads --sf-dir DIR --only W5,W8 --out FOLDER``."""

from .experiments import WORKLOADS  # noqa: F401
