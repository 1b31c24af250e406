"""Cost and accuracy measures: neighbourhood sizes, memory and overhead models, times and parallel efficiency."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: bytes of one point in the memory model
POINT_BYTES = 32
#: bytes for each node and each point: (T_o, T_p)
STRUCTURE_BYTES = {"pointer octree": (120, 8), "linear octree": (52, 0), "linear octree without centres": (28, 0), "non-complete octree": (128, 4)}

#: the same for the arrays of this library: boxes 48; codes, ranges and first children 33; eight children of 8; rows' numbers 8 or 4
LAYOUT_BYTES = {"linear octree": (82, 0), "pointer octree": (129, 8), "non-complete octree": (82, 4)}


def mean_neighbours(summary: DataFrame) -> DataFrame:
    """Centres without neighbours count."""
    return summary.agg(F.round(F.sum("n").cast("double") / F.count("*"), 6).alias("mu"), F.count("*").alias("centres"))


def node_ratio(tree: DataFrame) -> DataFrame:
    facts = tree.agg(F.count("*").alias("nodes"), F.sum(F.when(F.col("is_leaf"), F.col("cnt")).otherwise(0)).alias("points"))
    return facts.select("nodes", "points", F.round(F.col("nodes").cast("double") / F.col("points"), 6).alias("rho"))


def expected_overhead(node_bytes: float, point_bytes: float, rho: float) -> float:
    """Share of the cloud's size that a structure adds."""
    return (point_bytes + rho * node_bytes) / POINT_BYTES


def expected_bytes(n: int, node_bytes: float, point_bytes: float, rho: float) -> float:
    return n * (POINT_BYTES + point_bytes + rho * node_bytes)


def memory_table(tree: DataFrame) -> DataFrame:
    """(structure, bytes, overhead) of each structure for the tree's nodes; the non-complete octree leaves empty nodes out."""
    facts = tree.agg(F.count("*").alias("all"), F.sum((F.col("cnt") > 0).cast("long")).alias("full"), F.sum(F.when(F.col("is_leaf"), F.col("cnt")).otherwise(0)).alias("n"))
    out = None
    for name, (node, point) in STRUCTURE_BYTES.items():
        nodes = F.col("full") if name.startswith("non") else F.col("all")
        size = nodes * node + F.col("n") * point
        row = facts.select(F.lit(name).alias("structure"), size.cast("long").alias("bytes"), F.round(size.cast("double") / (F.col("n") * POINT_BYTES), 6).alias("overhead"))
        out = row if out is None else out.union(row)
    return out


def output_ratio(found: DataFrame) -> DataFrame:
    """Bytes of a result of ranges against bytes of the same neighbours' coordinates."""
    return found.agg((F.sum(F.lit(16.0) * F.col("n_ranges")) / F.sum(F.lit(24.0) * F.col("n"))).alias("ratio"))


def timed(make: Callable[[], DataFrame], runs: int = 1) -> float:
    """Mean seconds to compute a result in full, into a sink that drops it."""
    total = 0.0
    for _ in range(runs):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        total += time.perf_counter() - began
    return total / runs


def parallel_efficiency(times: dict[int, float]) -> dict[int, float]:
    """T1 / (p * Tp) for each number of cores."""
    return {p: times[1] / (p * t) for p, t in times.items()}


def speed_up(times: dict[int, float]) -> dict[int, float]:
    return {p: times[1] / t for p, t in times.items()}


def relative_runtime(changed: float, base: float) -> float:
    return changed / base


def assert_same_set(a: DataFrame, b: DataFrame) -> None:
    b = b.select(*a.columns)
    if not a.exceptAll(b).isEmpty() or not b.exceptAll(a).isEmpty():
        raise AssertionError("the results differ")
