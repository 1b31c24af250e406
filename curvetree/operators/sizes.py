"""How many nodes a single structure over a whole cloud has, counted by tasks: neither cloud nor structure is ever in one place.

The numbers are those of ``LinearOctree`` and ``PointerTree`` over all points in the order of their codes, tests hold them
against these.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import LEVELS, GridSpec
from ..plans.ranks import global_rank
from ..session import discard, materialise
from .local import STRUCTURES, LinearOctree, PointerTree
from .octree import build_counts

#: a branch of a kd-tree with so many points or fewer is built by one task
BRANCH_POINTS = 1_000_000


def count_nodes(cloud: DataFrame, grid: GridSpec, structure: str, curve: str = "hilbert", bucket: int = 128, branch: int = BRANCH_POINTS) -> int:
    options = {"bucket": bucket, "kind": "linear"} | STRUCTURES[structure]
    if options["kind"] == "kd":
        return _kd_nodes(cloud, grid, curve, options["bucket"], options.get("split", "median"), branch)
    if options["kind"] == "resolution":
        return _resolution_nodes(cloud, grid, max(grid.ext) / 16)
    coded = encode(cloud, grid, curve).select("code") if options["kind"] == "linear" else _halved(cloud, grid)
    counts = build_counts(coded, options["bucket"], LEVELS)
    if options["kind"] == "noncomplete":
        return max(1, counts.count())
    return 1 + 8 * counts.filter((F.col("cnt") > options["bucket"]) & (F.col("level") < LEVELS)).count()


def bytes_held(structure: str, nodes: int, points: int, boxes: bool = True) -> int:
    """Bytes of the arrays of a structure with so many nodes and points, by the arrays of a real one of one point."""
    one = np.zeros((1, 3))
    kind = STRUCTURES[structure]
    tree = PointerTree(one, (np.zeros(3), np.zeros(3)), **kind) if kind else LinearOctree(one, np.zeros(1, np.int64), GridSpec((0.0,) * 3, (0.0,) * 3), "hilbert", 1)
    return tree.bytes_of(nodes, points) if kind else tree.bytes_of(nodes, boxes)


def _paths(xyz: np.ndarray, grid: GridSpec) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each level from 0: the longest edge of each point's octant, and its octant's path, halved in reals as pointer
    octrees do it."""
    low = np.repeat(np.array(grid.lo)[None], len(xyz), axis=0)
    high = np.repeat((np.array(grid.lo) + np.array(grid.ext))[None], len(xyz), axis=0)
    path = np.zeros(len(xyz), np.int64)
    for level in range(LEVELS + 1):
        yield (high - low).max(axis=1, initial=0.0), path
        if level < LEVELS:
            mid = (low + high) / 2
            up = xyz >= mid
            path = path * 8 + up @ np.array([4, 2, 1])
            low, high = np.where(up, mid, low), np.where(up, high, mid)


def _xyz(b: pa.RecordBatch | pa.Table) -> np.ndarray:
    return np.stack([b.column(a).to_numpy() for a in "xyz"], axis=1)


def _halved(cloud: DataFrame, grid: GridSpec) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            *_, (_, path) = _paths(_xyz(b), grid)
            yield pa.RecordBatch.from_arrays([pa.array(path)], names=["code"])

    return cloud.select("x", "y", "z").mapInArrow(run, "code long")


def _resolution_nodes(cloud: DataFrame, grid: GridSpec, cell: float) -> int:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            held, live = [], np.ones(b.num_rows, bool)
            for level, (edge, path) in enumerate(_paths(_xyz(b), grid)):
                held.append((level, np.unique(path[live])))
                live &= edge > cell
                if not live.any():
                    break
            levels = np.concatenate([np.full(len(p), lv, np.int32) for lv, p in held])
            yield pa.RecordBatch.from_arrays([pa.array(levels), pa.array(np.concatenate([p for _, p in held]))], names=["level", "path"])

    return max(1, cloud.select("x", "y", "z").mapInArrow(run, "level int, path long").distinct().count())


def _kd_nodes(cloud: DataFrame, grid: GridSpec, curve: str, bucket: int, split: str, branch: int) -> int:
    """Nodes with more than ``branch`` points are halved together, level by level; what is below them is built by tasks.

    Each halving sorts a node's points by one axis and keeps the order before among equals, so the order in a node is by
    the axes used, the latest first, then by code and id. The point in the middle of that order parts the node."""
    if split != "median":
        raise ValueError("nodes are counted for kd-trees that split at the median")
    points = materialise(encode(cloud, grid, curve).select("pid", "x", "y", "z", "code", F.lit(1).cast("long").alias("node")), "kd-points")
    used: dict[int, tuple[str, ...]] = {1: ()}
    total, sealed = 0, []
    while True:
        held = points.filter(~F.col("node").isin(sealed)) if sealed else points
        facts = held.groupBy("node").agg(F.count("*").alias("n"), *(f(a).alias(f"{f.__name__}_{a}") for f in (F.min, F.max) for a in "xyz")).filter(F.col("n") > max(branch, bucket)).collect()
        wide = []
        for r in facts:  # at most the points divided by ``branch``
            span = [r[f"max_{a}"] - r[f"min_{a}"] for a in "xyz"]
            if any(span):
                axis = "xyz"[int(np.argmax(span))]
                used[r["node"]] = (axis, *(a for a in used[r["node"]] if a != axis))
                wide.append((r["node"], r["n"]))
            else:  # points in one place are never parted
                sealed.append(r["node"])
                total += 1
        if not wide:
            break
        keyed = _keyed(held.filter(F.col("node").isin([i for i, _ in wide])), used)
        near = {r["node"]: r["v"] for r in keyed.groupBy("node").agg(F.percentile_approx("k0", [0.499, 0.501], 10_000).alias("v")).collect()}
        between = lambda i: F.col("k0").between(F.lit(near[i][0]), F.lit(near[i][1]))
        at = F.col("node")
        inside = lambda: F.coalesce(*(F.when(at == i, between(i)) for i, _ in wide))
        below = lambda: F.coalesce(*(F.when(at == i, F.col("k0") < near[i][0]) for i, _ in wide))
        n = {r["node"]: (r["below"], r["inside"]) for r in keyed.groupBy("node").agg(F.sum(below().cast("long")).alias("below"), F.sum(inside().cast("long")).alias("inside")).collect()}
        if any(not n[i][0] <= size // 2 < n[i][0] + n[i][1] for i, size in wide):  # the quantiles were too far off
            near = {i: (float("-inf"), float("nan")) for i, _ in wide}
            n = {i: (0, size) for i, size in wide}
        ranked = global_rank(keyed.filter(inside()), ["node", "k0", "k1", "k2", "code", "pid"], "rank")
        start, wanted = 0, []
        for i, size in sorted(wide):
            wanted.append(start + size // 2 - n[i][0])
            start += n[i][1]
        cuts = {r["node"]: r for r in ranked.filter(F.col("rank").isin(wanted)).collect()}
        names = ("k0", "k1", "k2", "code", "pid")
        first = F.struct(*names)
        side = F.coalesce(*(F.when(at == i, F.when(first < F.struct(*(F.lit(r[c]).alias(c) for c in names)), 2 * i).otherwise(2 * i + 1)) for i, r in cuts.items()), at)
        dealt = materialise(_keyed(held, used).withColumn("node", side.cast("long")).select(*points.columns), "kd-points")
        discard(points)
        points = dealt
        total += len(cuts)
        used |= {kid: used[i] for i in cuts for kid in (2 * i, 2 * i + 1)}

    def build(key: tuple, rows: pa.Table) -> pa.Table:
        order = [rows.column(c).to_numpy() for c in ("pid", "code", *reversed(used[key[0].as_py()]))]
        xyz = _xyz(rows)[np.lexsort(order)]
        tree = PointerTree(xyz, (np.zeros(3), np.zeros(3)), kind="kd", bucket=bucket, split=split)
        return pa.table([pa.array([len(tree.lo)])], names=["nodes"])

    held = points.filter(~F.col("node").isin(sealed)) if sealed else points
    below = held.groupBy("node").applyInArrow(build, "nodes long").agg(F.sum("nodes")).first()[0]
    discard(points)
    return max(1, total + (below or 0))


def _keyed(points: DataFrame, used: dict[int, tuple[str, ...]]) -> DataFrame:
    """Adds k0, k1, k2: the axes that order each node, zero for those not used yet."""
    key = lambda j: F.coalesce(*(F.when(F.col("node") == i, F.col(axes[j])) for i, axes in used.items() if len(axes) > j), F.lit(0.0))
    return points.withColumns({f"k{j}": key(j) for j in range(3)})
