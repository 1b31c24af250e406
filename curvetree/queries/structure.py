"""Clouds, grids, codes, orders and trees."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.curves import encode, hilbert_decode, morton_decode, morton_encode
from ..functions.grid import fit_grid, quantise
from ..operators import costs, octree
from ..operators.reorder import jump_profile, rank_only, reorder
from ..sources import clouds
from . import sqltext as s

BUCKET = 16


def cloud(name: str, spark: SparkSession, d: str) -> DataFrame:
    return clouds.load(spark, d, name)


def grid_bounds(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in clouds.SPECS:
        row = clouds.load(spark, d, name).agg(*(f(a).alias(f"{n}{a}") for n, f in (("lo_", F.min), ("hi_", F.max)) for a in "xyz")).select(F.lit(name).alias("cloud"), "*")
        out = row if out is None else out.union(row)
    return out


def quantised(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return quantise(p, fit_grid(p)).select("pid", "cx", "cy", "cz")


def codes(curve: str, method: str | None, spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return encode(p, fit_grid(p), curve, method).select("pid", "code")


def round_trip(curve: str, spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    coded = encode(p, fit_grid(p), curve)
    if curve == "morton":
        back = coded.withColumns({f"d{a}": c for a, c in morton_decode(F.col("code")).items()})
    else:
        back = coded.withColumn("b", hilbert_decode(F.col("code"), 21)).select("*", *(F.col(f"b.c{a}").alias(f"d{a}") for a in "xyz"))
    same = (F.col("dx") == F.col("cx")) & (F.col("dy") == F.col("cy")) & (F.col("dz") == F.col("cz"))
    return back.agg(F.count("*").alias("points"), F.sum(same.cast("long")).alias("same"))


def axis_orders(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "embed")
    cells = quantise(p, fit_grid(p))
    return cells.select("pid", *(morton_encode(*(F.col(f"c{a}") for a in "xyz"), axis_order=o).alias(o) for o in ("xyz", "xzy", "yxz", "yzx", "zxy", "zyx")))


def continuity(spark: SparkSession, d: str) -> DataFrame:
    """Largest step, in cells of any axis, between the cells of successive codes of a level-4 grid that both hold orders, for both curves."""
    from pyspark.sql import Window

    p, out = clouds.load(spark, d, "order"), None
    grid = fit_grid(p)
    for curve in ("morton", "hilbert"):
        cells = encode(p, grid, curve).select(F.shiftright("code", 3 * 17).alias("code"), *(F.shiftright(f"c{a}", 17).alias(f"c{a}") for a in "xyz")).distinct()
        coded = cells.withColumn("part", F.expr("code div 512"))
        # the first cell of each run of 512 codes is also the last of the run before
        both = coded.union(coded.filter("code % 512 = 0 and code > 0").withColumn("part", F.col("part") - 1))
        spot = Window.partitionBy("part").orderBy("code")
        step = F.greatest(*(F.abs(F.col(f"c{a}") - F.lag(f"c{a}").over(spot)) for a in "xyz"))
        steps = both.select(step.alias("step"), (F.col("code") - F.lag("code").over(spot)).alias("on")).filter("on = 1")
        row = steps.agg(F.max("step").cast("long").alias("largest"), F.count("step").alias("steps")).select(F.lit(curve).alias("curve"), "largest", "steps")
        out = row if out is None else out.union(row)
    return out


def ranked(curve: str, spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return rank_only(p, curve, fit_grid(p))


def tree_of(spark: SparkSession, d: str, name: str = "event", curve: str = "hilbert", bucket: int = BUCKET, **options) -> DataFrame:
    p = clouds.load(spark, d, name)
    return octree.build_tree(encode(p, fit_grid(p), curve), bucket, 21, **options)


def leaves(spark: SparkSession, d: str) -> DataFrame:
    return tree_of(spark, d).filter("is_leaf").select("level", "prefix", "cnt")


def nodes(method: str, spark: SparkSession, d: str) -> DataFrame:
    return tree_of(spark, d, method=method).select("level", "prefix", "is_leaf", "cnt")


def ranges(spark: SparkSession, d: str) -> DataFrame:
    return tree_of(spark, d).select("level", "prefix", "idx_lo", "idx_hi", "code_lo", "code_hi")


def noncomplete(spark: SparkSession, d: str) -> DataFrame:
    return tree_of(spark, d, complete=False).select("level", "prefix", "cnt", "idx_lo", "idx_hi")


def profile(spark: SparkSession, d: str) -> DataFrame:
    return octree.depth_profile(tree_of(spark, d, "text", "morton"))


def shallow(spark: SparkSession, d: str) -> DataFrame:
    return octree.octants(tree_of(spark, d, "text", "morton"), 5).select("level", "prefix", "cnt", "is_leaf")


def ratios(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for bucket in (16, 32, 64, 128, 256):
        row = costs.node_ratio(tree_of(spark, d, "order", "morton", bucket)).select(F.lit(bucket).alias("bucket"), "*")
        out = row if out is None else out.union(row)
    return out


def overhead(spark: SparkSession, d: str) -> DataFrame:
    """The model's shares for the node ratios of the events' octree; the non-complete octree leaves empty nodes out."""
    n = F.sum(F.when(F.col("is_leaf"), F.col("cnt")).otherwise(0)).cast("double")
    facts, out = tree_of(spark, d, "event", "morton", 128).agg((F.count("*") / n).alias("all"), (F.sum((F.col("cnt") > 0).cast("long")) / n).alias("full")), None
    for name, (node, point) in costs.STRUCTURE_BYTES.items():
        rho = F.col("full" if name.startswith("non") else "all")
        row = facts.select(F.lit(name).alias("structure"), F.round(costs.expected_overhead(node, point, rho), 6).alias("overhead"))
        out = row if out is None else out.union(row)
    return out


def memory(spark: SparkSession, d: str) -> DataFrame:
    return costs.memory_table(tree_of(spark, d, "order", "morton", 128))


def jumps(spark: SparkSession, d: str) -> DataFrame:
    """Distances between successive points, summed up for each order."""
    p, out = clouds.load(spark, d, "order"), None
    for curve in ("none", "morton", "hilbert"):
        j = jump_profile(reorder(p, curve).select("idx", "x", "y", "z"), 4096)
        row = j.agg(F.count("*").alias("steps"), F.round(F.max("jump"), 6).alias("longest"), F.sum((F.col("jump") < 50).cast("long")).alias("short")).select(F.lit(curve).alias("curve"), "*")
        out = row if out is None else out.union(row)
    return out


QUERIES = {
    **{f"cloud_{n}": partial(cloud, n) for n in clouds.SPECS},
    "grid_bounds": grid_bounds,
    "quantise_cells": quantised,
    "morton_codes": partial(codes, "morton", None),
    "morton_codes_table": partial(codes, "morton", "table"),
    "morton_axis_orders": axis_orders,
    "morton_roundtrip": partial(round_trip, "morton"),
    "hilbert_codes": partial(codes, "hilbert", None),
    "hilbert_codes_native": partial(codes, "hilbert", "native"),
    "hilbert_roundtrip": partial(round_trip, "hilbert"),
    "curve_continuity": continuity,
    **{f"reorder_rank_{c}": partial(ranked, c) for c in ("none", "morton", "hilbert")},
    "octree_leaves": leaves,
    "octree_nodes": partial(nodes, "blocks"),
    "octree_nodes_iterative": partial(nodes, "iterative"),
    "octree_ranges": ranges,
    "octree_noncomplete": noncomplete,
    "octree_depth_profile": profile,
    "octree_shallow": shallow,
    "node_ratio": ratios,
    "overhead_model": overhead,
    "memory_table": memory,
    "jump_profile": jumps,
}

_T = f"WITH RECURSIVE {s.tree('event', 'hilbert', BUCKET)}"
_TEXT = f"WITH RECURSIVE {s.tree('text', 'morton', BUCKET)}"


def _ratio_sql(bucket: int) -> str:
    return f"SELECT {bucket} AS bucket, * FROM (WITH RECURSIVE {s.tree('order', 'morton', bucket)} SELECT count(*) AS nodes, sum(CASE WHEN is_leaf THEN cnt ELSE 0 END)::BIGINT AS points, round(count(*)::DOUBLE / sum(CASE WHEN is_leaf THEN cnt ELSE 0 END), 6) AS rho FROM t) x{bucket}"


def _jump_sql(curve: str) -> str:
    rank = "row_number() OVER (ORDER BY pid) - 1" if curve == "none" else "idx"
    return f"""SELECT '{curve}' AS curve, count(*) AS steps, round(max(j), 6) AS longest, sum((j < 50)::INT)::BIGINT AS short FROM (WITH RECURSIVE {s.coded('order', curve)}, o AS (SELECT x, y, z, {rank} AS pos FROM k)
SELECT sqrt((lead(x) OVER w - x) * (lead(x) OVER w - x) + (lead(y) OVER w - y) * (lead(y) OVER w - y) + (lead(z) OVER w - z) * (lead(z) OVER w - z)) AS j FROM o WINDOW w AS (ORDER BY pos)) x WHERE j IS NOT NULL"""


def _step_sql(curve: str) -> str:
    step = ", ".join(f"abs(c{a} - lag(c{a}) OVER w)" for a in "xyz")
    return f"""SELECT '{curve}' AS curve, max(step)::BIGINT AS largest, count(step) AS steps FROM (WITH RECURSIVE {s.coded('order', curve)}, f AS (SELECT DISTINCT code >> 51 AS code, cx >> 17 AS cx, cy >> 17 AS cy, cz >> 17 AS cz FROM k)
SELECT greatest({step}) AS step, code - lag(code) OVER w AS on_ FROM f WINDOW w AS (ORDER BY code)) x WHERE on_ = 1"""


_STRUCT = "VALUES ('pointer octree', 120, 8, false), ('linear octree', 52, 0, false), ('linear octree without centres', 28, 0, false), ('non-complete octree', 128, 4, true)"
ORACLE = {
    **{f"cloud_{n}": sql for n, sql in s.CLOUD.items()},
    "grid_bounds": " UNION ALL ".join(f"SELECT '{n}' AS cloud, min(x) AS lo_x, min(y) AS lo_y, min(z) AS lo_z, max(x) AS hi_x, max(y) AS hi_y, max(z) AS hi_z FROM ({sql}) {n}_" for n, sql in s.CLOUD.items()),
    "quantise_cells": f"WITH {s.cells('order')} SELECT pid, cx::INT AS cx, cy::INT AS cy, cz::INT AS cz FROM c",
    **{k: f"WITH {s.coded('order', 'morton')} SELECT pid, code FROM k" for k in ("morton_codes", "morton_codes_table")},
    "morton_axis_orders": f"WITH {s.cells('embed')} SELECT pid, " + ", ".join(f"({s.morton(*(f'c{a}' for a in o))})::BIGINT AS {o}" for o in ("xyz", "xzy", "yxz", "yzx", "zxy", "zyx")) + " FROM c",
    **{f"{c}_roundtrip": "SELECT count(*) AS points, count(*) AS same FROM orders" for c in ("morton", "hilbert")},
    **{k: f"WITH RECURSIVE {s.coded('order', 'hilbert')} SELECT pid, code FROM k" for k in ("hilbert_codes", "hilbert_codes_native")},
    "curve_continuity": " UNION ALL ".join(map(_step_sql, ("morton", "hilbert"))),
    "reorder_rank_none": f"WITH p AS ({s.CLOUD['order']}) SELECT pid, row_number() OVER (ORDER BY pid) - 1 AS idx FROM p",
    **{f"reorder_rank_{c}": f"WITH RECURSIVE {s.coded('order', c)} SELECT pid, idx FROM k" for c in ("morton", "hilbert")},
    "octree_leaves": f"{_T} SELECT level, prefix, cnt FROM t WHERE is_leaf",
    **{k: f"{_T} SELECT level, prefix, is_leaf, cnt FROM t" for k in ("octree_nodes", "octree_nodes_iterative")},
    "octree_ranges": f"{_T} SELECT level, prefix, idx_lo, idx_hi, prefix << (3 * (21 - level)) AS code_lo, ((prefix << (3 * (21 - level))) + ((1::BIGINT << (3 * (21 - level) - 1)) - 1) + (1::BIGINT << (3 * (21 - level) - 1))) AS code_hi FROM t WHERE level < 21",
    "octree_noncomplete": f"{_T} SELECT level, prefix, cnt, idx_lo, idx_hi FROM t WHERE cnt > 0",
    "octree_depth_profile": f"{_TEXT} SELECT level, count(*) AS nodes, sum(is_leaf::INT)::BIGINT AS leaves, sum((cnt = 0)::INT)::BIGINT AS empty, max(cnt) AS largest FROM t GROUP BY level",
    "octree_shallow": f"{_TEXT} SELECT level, prefix, cnt, is_leaf FROM t WHERE level <= 5",
    "node_ratio": " UNION ALL ".join(map(_ratio_sql, (16, 32, 64, 128, 256))),
    "overhead_model": f"WITH RECURSIVE {s.tree('event', 'morton', 128)}, f AS (SELECT count(*) / sum(CASE WHEN is_leaf THEN cnt ELSE 0 END)::DOUBLE AS every_, sum((cnt > 0)::INT) / sum(CASE WHEN is_leaf THEN cnt ELSE 0 END)::DOUBLE AS full_n FROM t), v(structure, o, p, sparse) AS ({_STRUCT}) SELECT structure, round((p + (CASE WHEN sparse THEN full_n ELSE every_ END) * o) / 32.0::DOUBLE, 6) AS overhead FROM v, f",
    "memory_table": f"WITH RECURSIVE {s.tree('order', 'morton', 128)}, f AS (SELECT count(*) AS every_, sum((cnt > 0)::INT) AS full_n, sum(CASE WHEN is_leaf THEN cnt ELSE 0 END) AS n FROM t), v(structure, o, p, sparse) AS ({_STRUCT}) SELECT structure, ((CASE WHEN sparse THEN full_n ELSE every_ END) * o + n * p)::BIGINT AS bytes, round(((CASE WHEN sparse THEN full_n ELSE every_ END) * o + n * p)::DOUBLE / (n * 32), 6) AS overhead FROM v, f",
    "jump_profile": " UNION ALL ".join(map(_jump_sql, ("none", "morton", "hilbert"))),
}
