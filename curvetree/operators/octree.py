"""The linear octree over curve-ordered points, as a table of nodes.

A node is (level, prefix): the octant whose points' codes start with the prefix. It is split while it holds more than
``bucket`` points and levels remain. Every node, leaf or internal, is one range of codes and one range of indices.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.curves import np_decode
from ..functions.grid import GridSpec
from ..plans.ranks import running_start
from ..session import materialise

BLOCK = 7


def _parents(counts: DataFrame, by: int) -> DataFrame:
    return counts.groupBy(F.shiftright("prefix", 3 * by).alias("prefix")).agg(F.sum("cnt").alias("cnt"))


def build_counts(coded: DataFrame, bucket: int, levels: int) -> DataFrame:
    """(level, prefix, cnt) of all non-empty nodes: at most three scans of the codes.

    Codes are counted at every seventh level (combined before the shuffle); levels between are sums of those. Only
    codes under overfull nodes are read again for the next seven.
    """
    codes, parts, top, done = coded.select("code"), [], None, 0
    while True:
        to = min(done + BLOCK, levels)
        counts = codes.groupBy(F.shiftright("code", 3 * (levels - to)).alias("prefix")).agg(F.count("*").alias("cnt"))
        counts = materialise(counts, "counts")
        block = None
        for level in range(done if done == 0 else done + 1, to + 1):
            rolled = (counts if level == to else _parents(counts, to - level)).select(F.lit(level).alias("level"), "prefix", "cnt")
            block = rolled if block is None else block.union(rolled)
        parts.append(block)
        top = counts.filter(F.col("cnt") > bucket)
        if to == levels or top.isEmpty():
            break
        shift = 3 * (levels - to)
        codes = codes.join(top.select(F.col("prefix").alias("__p")), F.shiftright("code", shift) == F.col("__p"), "left_semi")
        done = to
    nodes = parts[0]
    for p in parts[1:]:
        nodes = nodes.union(p)
    nodes = materialise(nodes, "nodes")
    over = nodes.filter(F.col("cnt") > bucket).select((F.col("level") + 1).alias("level"), F.col("prefix").alias("__up"))
    # a node exists if its parent is overfull: all nodes above an overfull node are overfull too
    below = nodes.join(over, (nodes.level == over.level) & (F.shiftright(nodes.prefix, 3) == F.col("__up")), "left_semi")
    return nodes.filter("level = 0").union(below)


def build_counts_iterative(coded: DataFrame, bucket: int, levels: int) -> DataFrame:
    """The same nodes by the literal refinement: one count for each level, over what the last level left overfull."""
    spark, out = coded.sparkSession, []
    open_codes, level = coded.select("code"), 0
    while level <= levels:
        shift = 3 * (levels - level)
        counts = materialise(open_codes.groupBy(F.shiftright("code", shift).alias("prefix")).agg(F.count("*").alias("cnt")), "round")
        out.append(counts.select(F.lit(level).alias("level"), "prefix", "cnt"))
        over = counts.filter(F.col("cnt") > bucket)
        if over.isEmpty():
            break
        open_codes = open_codes.join(over.select(F.col("prefix").alias("__p")), F.shiftright("code", shift) == F.col("__p"), "left_semi")
        level += 1
    nodes = out[0] if out else spark.createDataFrame([], "level int, prefix long, cnt long")
    for p in out[1:]:
        nodes = nodes.union(p)
    return nodes


def build_tree(coded: DataFrame, bucket: int, levels: int, complete: bool = True, method: str = "blocks") -> DataFrame:
    """level, prefix, is_leaf, cnt, code_lo, code_hi (inclusive), idx_lo, idx_hi (exclusive).

    ``complete`` adds the empty children of internal nodes. Leaves' ranges are running sums of counts in code order, by
    two levels; an internal node's range spans its descendants'.
    """
    counts = (build_counts if method == "blocks" else build_counts_iterative)(coded, bucket, levels)
    counts = materialise(counts.withColumn("is_leaf", (F.col("cnt") <= bucket) | (F.col("level") == levels)), "tree")
    if complete:
        children = counts.filter(~F.col("is_leaf")).select((F.col("level") + 1).alias("level"), F.explode(F.expr("sequence(prefix * 8L, prefix * 8L + 7L)")).alias("prefix"))
        empty = children.join(counts.select("level", "prefix"), ["level", "prefix"], "left_anti")
        counts = counts.unionByName(empty.select("level", "prefix", F.lit(0).cast("long").alias("cnt"), F.lit(True).alias("is_leaf")))
    return node_ranges(counts, levels)


def node_ranges(counts: DataFrame, levels: int) -> DataFrame:
    lo = F.expr(f"shiftleft(prefix, ({levels} - level) * 3)")
    # inclusive ends: the exclusive end of the last octant would be 2^63
    coded = counts.withColumns({"code_lo": lo, "code_hi": lo.bitwiseOR(F.expr(f"~shiftleft(-1L, ({levels} - level) * 3)"))})
    leaves = coded.filter("is_leaf").select("level", "prefix", "code_lo", "cnt")
    group = F.shiftright("code_lo", max(0, 3 * (levels - 5)))  # 32,768 groups at most
    spots = running_start(leaves, group, "code_lo", "cnt", "idx_lo").select("level", "prefix", "idx_lo", (F.col("idx_lo") + F.col("cnt")).alias("idx_hi"))
    spots = materialise(spots, "leaf-ranges")
    above = spots.filter("level > 0").select(F.explode(F.expr("sequence(0, level - 1)")).alias("up"), "level", "prefix", "idx_lo", "idx_hi")
    above = above.groupBy(F.col("up").alias("level"), F.expr("shiftright(prefix, 3 * (level - up))").alias("prefix")).agg(F.min("idx_lo").alias("idx_lo"), F.max("idx_hi").alias("idx_hi"))
    ranges = spots.unionByName(above)
    return coded.join(ranges, ["level", "prefix"]).select("level", "prefix", "is_leaf", "cnt", "code_lo", "code_hi", "idx_lo", "idx_hi")


def with_boxes(tree: DataFrame, grid: GridSpec, curve: str, pad: bool = True) -> DataFrame:
    """Adds x0, x1, y0, y1, z0, z1: the octants' boxes, decoded from their prefixes."""
    names = ("x0", "x1", "y0", "y1", "z0", "z1")

    @F.pandas_udf(", ".join(f"{n} double" for n in names))
    def box(level: pd.Series, prefix: pd.Series) -> pd.DataFrame:
        lo, hi = node_boxes(level.to_numpy(), prefix.to_numpy(), grid, curve, pad)
        return pd.DataFrame({n: (lo if n[1] == "0" else hi)[:, "xyz".index(n[0])] for n in names})

    return tree.withColumn("__b", box("level", "prefix")).select(*tree.columns, *(F.col(f"__b.{n}").alias(n) for n in names))


def node_boxes(level: np.ndarray, prefix: np.ndarray, grid: GridSpec, curve: str, pad: bool = True) -> tuple[np.ndarray, np.ndarray]:
    cells = np.zeros((len(level), 3), np.int64)
    for n in np.unique(level):
        at = level == n
        cells[at] = np_decode(prefix[at].astype(np.int64), curve, int(n)) if n else 0
    return grid.np_boxes(level, cells, pad)


def depth_profile(tree: DataFrame) -> DataFrame:
    return tree.groupBy("level").agg(F.count("*").alias("nodes"), F.sum(F.col("is_leaf").cast("long")).alias("leaves"), F.sum((F.col("cnt") == 0).cast("long")).alias("empty"), F.max("cnt").alias("largest"))


def octants(tree: DataFrame, max_depth: int) -> DataFrame:
    """Nodes down to a depth, for drawing."""
    return tree.filter(F.col("level") <= max_depth)
