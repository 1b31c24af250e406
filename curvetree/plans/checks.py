"""Assertions on physical plans."""

from __future__ import annotations

import contextlib
import io

from pyspark.sql import DataFrame

FORBIDDEN = ("CartesianProduct", "BroadcastNestedLoopJoin")


def plan_text(df: DataFrame) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def problems(df: DataFrame, allow: tuple[str, ...] = ()) -> list[str]:
    """Nested loops, Cartesian products, and windows or exchanges that put all rows into one task."""
    text = plan_text(df)
    out = [f for f in FORBIDDEN if f in text and f not in allow]
    if "SinglePartition" in text and "Window" in text and "SinglePartition" not in allow:
        out.append("a window over a single partition")
    return out
