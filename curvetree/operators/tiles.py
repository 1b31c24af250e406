"""The tile engine: centres are routed to tiles by the top tier, tiles search with a local structure, results are merged.

Only centres move, to tiles they can have neighbours in; tiles wholly inside a kernel answer from the top tier's index
ranges without any point being read. Of the stored points only the folders of routed tiles are read. Centres of one
tile go to it in salted groups of bounded size, in the order they came; inside a task they follow the curve.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.curves import np_encode
from ..functions.grid import GridSpec
from ..functions.kernels import Kernel
from ..session import materialise
from .local import COUNTERS, LINEAR, NONE, OUTPUT, Walk, build_local
from .octree import node_boxes
from .reorder import Index, Tiles, part_of

SALT_CENTRES = 20_000
#: the forms of a result: index ranges, single indices, coordinates, or numbers only
FORMS = {"ranges": "array<struct<lo:bigint,hi:bigint>>", "indices": "array<bigint>", "coords": "array<struct<x:double,y:double,z:double>>", "count": None}
#: (first entry of each centre's list, columns of all lists end to end) to rows
Fold = Callable[[np.ndarray, list[np.ndarray]], pa.RecordBatch]


class TopTier(Walk):
    """The tiles and the octants above them as arrays, small enough for every task. Its leaves are the tiles."""

    def __init__(self, tiles: Tiles, grid: GridSpec, curve: str):
        number = np.arange(len(tiles))
        levels: list[dict[str, np.ndarray]] = []  # from the deepest up; nodes of a level in the order of codes
        for lv in range(int(tiles.level.max(initial=-1)), -1, -1):
            own = np.flatnonzero(tiles.level == lv)
            here = {"prefix": tiles.prefix[own], "tile": number[own], "first": number[own], "last": number[own], "kid": np.zeros(len(own), np.int64), "n": np.zeros(len(own), np.int64)}
            if levels:
                below = levels[-1]
                up, at, n = np.unique(below["prefix"] >> 3, return_index=True, return_counts=True)
                inner = {"prefix": up, "tile": np.full(len(up), -1), "first": below["first"][at], "last": below["last"][at + n - 1], "kid": at, "n": n}
                here = {k: np.concatenate((here[k], inner[k])) for k in here}
                order = np.lexsort((here["first"], here["prefix"]))
                here = {k: v[order] for k, v in here.items()}
            levels.append(here)
        levels.reverse()
        size = [len(x["prefix"]) for x in levels]
        join = lambda k: np.concatenate([x[k] for x in levels]) if levels else NONE
        depth, self.prefix, self.tile = np.repeat(np.arange(len(levels)), size), join("prefix"), join("tile")
        self.kid, self.kid_n = join("kid") + np.repeat(np.cumsum(size), size).astype(np.int64), join("n")
        self.leaf, self.first, self.last = self.tile >= 0, join("first"), join("last")
        self.lo, self.hi = tiles.idx_lo[self.first], tiles.idx_hi[self.last]
        self.sums = np.concatenate((np.zeros(1, np.int64), np.cumsum(tiles.pid_sum)))
        self.tile_level, self.tile_prefix, self.tile_lo = tiles.level, tiles.prefix, tiles.idx_lo
        self.box_lo, self.box_hi = node_boxes(depth, self.prefix, grid, curve) if levels else (np.zeros((0, 3)), np.zeros((0, 3)))

    def children(self, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = self.kid_n[node]
        ends = np.cumsum(n)
        return n, np.arange(ends[-1] if len(ends) else 0) + np.repeat(self.kid[node] - ends + n, n)

    def route(self, kernel: Kernel, q: np.ndarray, r: np.ndarray, bulk: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(centre, tile) to search, (centre, node) taken whole."""
        out: list[list[np.ndarray]] = [[NONE], [NONE], [NONE], [NONE]]
        who = np.arange(len(q) if len(self.lo) else 0)
        node = np.zeros(len(who), np.int64)
        while len(who):
            place = kernel.np_classify(self.box_lo[node], self.box_hi[node], q[who], r[who])
            whole = (place == 1) & bulk
            stop = (place != -1) & ~whole & self.leaf[node]
            go = (place != -1) & ~whole & ~self.leaf[node]
            for x, y in zip(out, (who[stop], self.tile[node[stop]], who[whole], node[whole]), strict=True):
                x.append(y)
            count, node = self.children(node[go])
            who = np.repeat(who[go], count)
        return tuple(np.concatenate(x) for x in out)


def _axes(b: pa.RecordBatch | pa.Table, names: tuple[str, str, str]) -> np.ndarray:
    return np.stack([b.column(c).to_numpy() for c in names], axis=1)


def _arrays(group: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    order = np.argsort(group.column("idx").to_numpy(), kind="stable")
    take = lambda c: group.column(c).to_numpy()[order]
    return np.stack([take("x"), take("y"), take("z")], axis=1), take("code"), take("pid"), take("idx")


def _along(index: Index, q: np.ndarray, cid: np.ndarray) -> np.ndarray:
    """What orders centres: their code, or in a cloud without order their id."""
    return np_encode(index.grid.np_cells(q), index.curve, index.grid.levels) if index.ordered else cid


class _Chunks:
    """Numbers the rows that a task routes, in chunks of SALT_CENTRES."""

    def __init__(self):
        context = TaskContext.get()
        self.base, self.seen = (context.partitionId() if context else 0) << 16, 0

    def next(self, n: int) -> np.ndarray:
        out = self.base + (self.seen + np.arange(n)) // SALT_CENTRES
        self.seen += n
        return out


def _dealt(index: Index, routed: DataFrame, carry: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """(points of the routed tiles, centres), both with tile and salt. Tiles with many centres are searched by several
    tasks. ``routed`` is stored; its counts have one row a tile, and there are no more tiles than the index allows."""
    counts = materialise(routed.groupBy("tile").agg(F.ceil(F.count("*") / SALT_CENTRES).cast("int").alias("salts")), "routed-tiles")
    points = index.points
    if index.parts > 1:
        wanted = [r[0] for r in counts.select(part_of("tile", len(index.tiles), index.parts).alias("p")).distinct().collect()]  # at most MOST_PARTS
        points = points.filter(F.col("part").isin(wanted))
    centres = routed.join(F.broadcast(counts), "tile").withColumn("salt", F.pmod(F.col("chunk"), F.col("salts")).cast("int")).drop("salts", "chunk")
    rows = points.select("pid", "x", "y", "z", "code", "idx", "tile", *carry).join(F.broadcast(counts), "tile")
    rows = rows.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    # a number of its own, as adaptive execution would put small tables together: searching them is work all the same
    context = points.sparkSession.sparkContext
    tasks = max(4 * context.defaultParallelism, int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return rows.repartition(tasks, "tile", "salt"), centres.repartition(tasks, "tile", "salt")


def radius_tiles(index: Index, centres: DataFrame, kernel: Kernel, r: float | None, structure: str = "ranges", cell: float = 0.0, contain_leaves: bool = True, tight: bool = False, output: str | None = None) -> DataFrame:
    """(cid, n, pid_sum, [ranges | indices | coords,] nodes, ..., n_ranges) for each centre and tile with a hit or work.

    ``output``: by default what the structure gives: ranges its index ranges, the non-complete octree coordinates, all
    others an index for every neighbour. ``n_ranges`` counts the entries of that list. ``r`` None: centres carry their
    own column r. Merge with radius_summary, merge_ranges or merge_lists.
    """
    output = output or OUTPUT.get(structure, "indices")
    if not index.ordered and (structure in LINEAR or output == "ranges"):
        raise ValueError("ranges and linear octrees need an index along a curve")
    spark, grid, curve, bucket = index.points.sparkSession, index.grid, index.curve if index.ordered else "morton", index.bucket
    shared = spark.sparkContext.broadcast(TopTier(index.tiles, grid, curve))  # bounded by the number of tiles
    own = centres if r is None else centres.withColumn("r", F.lit(float(r)))
    # whole tiles have no coordinates to give, and a cloud without order has no ranges of whole tiles
    bulk = structure in ("ranges", "prune", "noncomplete") and output != "coords" and index.ordered
    plain_index = Index(None, None, grid, index.curve, bucket)
    routing = "cid long, qx double, qy double, qz double, r double, along long, tile int, lo long, hi long, pid_sum long, chunk long"
    route_names = [c.split()[0] for c in routing.split(", ")]

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tier, chunks = shared.value, _Chunks()
        for b in batches:
            if not b.num_rows:
                continue
            cid, q, rr = b.column("cid").to_numpy(), _axes(b, ("qx", "qy", "qz")), b.column("r").to_numpy()
            who, tile, taken, node = tier.route(kernel, q, rr, bulk)
            both = np.concatenate((who, taken))
            gap, known = pa.nulls(len(who), pa.int64()), np.concatenate((tile, np.zeros(len(taken), np.int64)))
            late = lambda x: pa.concat_arrays([gap, pa.array(x.astype(np.int64))])
            mask = np.concatenate((np.zeros(len(who), bool), np.ones(len(taken), bool)))
            sums = tier.sums[tier.last[node] + 1] - tier.sums[tier.first[node]]
            yield pa.RecordBatch.from_arrays([
                *(pa.array(x) for x in (cid[both], q[both, 0], q[both, 1], q[both, 2], rr[both], _along(plain_index, q, cid)[both].astype(np.int64))),
                pa.array(known.astype(np.int32), mask=mask), late(tier.lo[node]), late(tier.hi[node]), late(sums), pa.array(chunks.next(len(both))),
            ], names=route_names)

    routed = materialise(own.select("cid", "qx", "qy", "qz", "r").mapInArrow(route, routing), "routed")
    count = F.col("hi") - F.col("lo")
    list_of = {"ranges": F.array(F.struct("lo", "hi")), "indices": F.sequence("lo", F.col("hi") - 1)}
    entries = {"ranges": F.lit(1), "indices": count, "count": F.lit(0)}
    made = {c: F.lit(0) for c in COUNTERS} | {"contained": F.lit(1), "nodes": F.lit(1), "bulk": count, "n_ranges": entries.get(output, F.lit(0))}
    lists = [] if FORMS[output] is None else [output]
    taken = routed.filter("tile is null").select("cid", count.alias("n"), "pid_sum", *(list_of[output].alias(output) for _ in lists if output in list_of), *(v.cast("long").alias(c) for c, v in made.items()))
    points, asked = _dealt(index, routed.filter("tile is not null").drop("lo", "hi", "pid_sum"))
    names = ["cid", "n", "pid_sum", *lists, *COUNTERS]

    def search(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        tier, tile = shared.value, key[0].as_py()
        xyz, codes, pid, idx = _arrays(left)
        root = int(tier.tile_level[tile]), int(tier.tile_prefix[tile])
        box = node_boxes(np.array([root[0]]), np.array([root[1]]), grid, curve)
        tree = build_local(structure, xyz, codes, grid, curve, bucket, root, (box[0][0], box[1][0]), cell, tight)
        right = right.take(pa.array(np.argsort(right.column("along").to_numpy(), kind="stable")))
        q, rr = _axes(right, ("qx", "qy", "qz")), right.column("r").to_numpy()
        sums, n = np.zeros(len(q), np.int64), np.zeros(len(q), np.int64)
        if output == "ranges":
            who, lo, hi, work = tree.radius(kernel, q, rr, structure, contain_leaves)
            total = np.concatenate(([0], np.cumsum(pid)))
            np.add.at(sums, who, total[hi] - total[lo])
            np.add.at(n, who, hi - lo)
            base = int(idx[0]) if len(idx) else 0
            values = pa.StructArray.from_arrays([pa.array(lo + base), pa.array(hi + base)], names=["lo", "hi"])
        else:
            who, rows, work = tree.hits(kernel, q, rr, structure, contain_leaves)
            total = np.concatenate(([0], np.cumsum(pid[rows])))
            edges = np.searchsorted(who, np.arange(len(q) + 1))
            sums, n = total[edges[1:]] - total[edges[:-1]], np.diff(edges)
            values = pa.array(idx[rows]) if output == "indices" else pa.StructArray.from_arrays([pa.array(xyz[rows, i]) for i in range(3)], names=["x", "y", "z"])
            work[:, 5] *= output != "count"
        cuts = np.searchsorted(who, np.arange(len(q) + 1)).astype(np.int32)
        found = [pa.ListArray.from_arrays(pa.array(cuts), values)] if lists else []
        return pa.table([right.column("cid"), pa.array(n), pa.array(sums), *found, *(pa.array(work[:, i]) for i in range(len(COUNTERS)))], names=names)

    schema = "cid long, n long, pid_sum long, " + "".join(f"{c} {FORMS[c]}, " for c in lists) + ", ".join(f"{c} long" for c in COUNTERS)
    tested = points.groupBy("tile", "salt").cogroup(asked.groupBy("tile", "salt")).applyInArrow(search, schema)
    return tested.unionByName(taken) if bulk else tested


def radius_summary(index: Index, centres: DataFrame, found: DataFrame) -> DataFrame:
    """(cid, n, pid_sum) with a row for every centre, hits or none."""
    per = found.groupBy("cid").agg(F.sum("n").alias("n"), F.sum("pid_sum").alias("pid_sum"))
    out = centres.select("cid").join(per, "cid", "left")
    return out.select("cid", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("n", "pid_sum")))


def work_counters(found: DataFrame) -> DataFrame:
    return found.groupBy("cid").agg(*(F.sum(c).alias(c) for c in COUNTERS))


def merge_ranges(found: DataFrame, centres: DataFrame | None = None) -> DataFrame:
    """(cid, n, ranges): each centre's ranges sorted, touching ones put together, empty for centres without hits."""
    flat = found.groupBy("cid").agg(F.sum("n").alias("n"), F.array_sort(F.flatten(F.collect_list("ranges"))).alias("rs"))
    step = lambda acc, s: F.when((F.size(acc) > 0) & (F.element_at(acc, -1)["hi"] == s["lo"]), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.element_at(acc, -1)["lo"].alias("lo"), s["hi"].alias("hi"))))).otherwise(F.concat(acc, F.array(s)))
    empty = F.expr(f"cast(array() as {FORMS['ranges']})")
    out = flat.select("cid", "n", F.aggregate("rs", empty, step).alias("ranges"))
    if centres is None:
        return out
    return centres.select("cid").join(out, "cid", "left").select("cid", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("ranges", empty).alias("ranges"))


def merge_lists(found: DataFrame, centres: DataFrame | None = None) -> DataFrame:
    """(cid, n, indices or coords): each centre's list in order, empty for centres without hits."""
    form = "indices" if "indices" in found.columns else "coords"
    out = found.groupBy("cid").agg(F.sum("n").alias("n"), F.array_sort(F.flatten(F.collect_list(form))).alias(form))
    if centres is None:
        return out
    empty = F.expr(f"cast(array() as {FORMS[form]})")
    return centres.select("cid").join(out, "cid", "left").select("cid", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce(form, empty).alias(form))


def neighbours(index: Index, centres: DataFrame, kernel: Kernel, r: float | None, structure: str = "ranges", exclude_self: bool = False, min_count: int = 0, limit: int | None = None, **options) -> DataFrame:
    """(cid, n, ranges | indices | coords), one row a centre. ``exclude_self``: the point whose pid is the centre's id is no
    neighbour of it. ``min_count``: centres with fewer neighbours are left out. ``limit``: of lists of indices or
    coordinates the first so many; n still counts all."""
    found = radius_tiles(index, centres, kernel, r, structure, **options)
    form = next((f for f in FORMS if f in found.columns), None)
    if form is None:
        raise ValueError("a form with a list")
    out = merge_ranges(found, centres) if form == "ranges" else merge_lists(found, centres)
    if exclude_self:
        me = index.points.select(F.col("pid").alias("cid"), F.col("idx").alias("__i"), F.struct("x", "y", "z").alias("__at"))
        held = out.join(me, "cid", "left")
        if form == "ranges":
            pieces = lambda s: F.filter(F.array(F.struct(s["lo"].alias("lo"), F.least(s["hi"], F.coalesce(F.col("__i"), s["hi"])).alias("hi")), F.struct(F.greatest(s["lo"], F.coalesce(F.col("__i") + 1, s["hi"])).alias("lo"), s["hi"].alias("hi"))), lambda p: p["lo"] < p["hi"])
            split = F.flatten(F.transform("ranges", lambda s: F.when((s["lo"] <= F.col("__i")) & (F.col("__i") < s["hi"]), pieces(s)).otherwise(F.array(s))))
            left = held.select("cid", split.alias("ranges"))
            n = F.aggregate("ranges", F.lit(0).cast("long"), lambda a, s: a + s["hi"] - s["lo"])
            out = left.select("cid", n.alias("n"), "ranges")
        else:
            mine = F.col("__i") if form == "indices" else F.col("__at")
            spot = F.array_position(form, mine).cast("int")
            kept = F.when(F.coalesce(spot, F.lit(0)) == 0, F.col(form)).otherwise(F.concat(F.slice(form, 1, F.greatest(spot - 1, F.lit(0))), F.slice(form, F.greatest(spot + 1, F.lit(1)), F.greatest(F.size(form) - spot, F.lit(0)))))
            out = held.select("cid", F.size(kept).cast("long").alias("n"), kept.alias(form))
    out = out.filter(F.col("n") >= min_count) if min_count else out
    if limit is not None:
        if form == "ranges":
            raise ValueError("a limit needs a list of single neighbours")
        out = out.withColumn(form, F.slice(form, 1, limit))
    return out


def expand_ranges(ranges: DataFrame, points: DataFrame, chunk: int = 4096) -> DataFrame:
    """(cid, pid): ranges are cut at chunk borders and joined to points by chunk, so the range condition is only a filter."""
    flat = ranges.select("cid", F.explode("ranges").alias("s")).select("cid", F.col("s.lo").alias("lo"), F.col("s.hi").alias("hi"))
    cut = flat.withColumn("c", F.explode(F.sequence(F.expr(f"lo div {chunk}"), F.expr(f"(hi - 1) div {chunk}"))))
    keyed = points.select("pid", "idx", F.expr(f"idx div {chunk}").alias("c"))
    return cut.join(keyed, "c").filter((F.col("idx") >= F.col("lo")) & (F.col("idx") < F.col("hi"))).select("cid", "pid")


def aggregate_ranges(ranges: DataFrame, points: DataFrame, value: str, chunk: int = 4096) -> DataFrame:
    """(cid, n, total) of ``value`` without expanding: whole chunks by their sums, the two ends by prefix sums inside a chunk."""
    keyed = points.select("idx", F.col(value).alias("v"), F.expr(f"idx div {chunk}").alias("c"))
    spot = Window.partitionBy("c").orderBy("idx")
    prefix = keyed.select("idx", "c", F.coalesce(F.sum("v").over(spot.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), "v")
    flat = ranges.select("cid", F.explode("ranges").alias("s")).select("cid", F.col("s.lo").alias("lo"), F.col("s.hi").alias("hi"))
    cut = flat.withColumn("c", F.explode(F.sequence(F.expr(f"lo div {chunk}"), F.expr(f"(hi - 1) div {chunk}"))))
    cut = cut.select("cid", F.greatest("lo", F.col("c") * chunk).alias("lo"), (F.least("hi", (F.col("c") + 1) * chunk) - 1).alias("last"))
    a = cut.join(prefix.select(F.col("idx").alias("lo"), F.col("before").alias("b0")), "lo")
    b = a.join(prefix.select(F.col("idx").alias("last"), (F.col("before") + F.col("v")).alias("b1")), "last")
    return b.groupBy("cid").agg(F.sum(F.col("last") - F.col("lo") + 1).alias("n"), F.sum(F.col("b1") - F.col("b0")).alias("total"))


def knn_lists(index: Index, centres: DataFrame, k: int, structure: str = "prune", cell: float = 0.0, method: str = "batch", carry: tuple[str, ...] = (), fold: Fold | None = None, folded: str = "") -> DataFrame:
    """(cid, d2, pid, ...), a row for each centre with arrays of its k nearest in order: exact, ties by own point first, then
    pid. ``carry``: long columns of the index's points that come along, an array each.

    A centre is first searched in the tile it lies in. The distance of its k-th nearest there, or one that surely holds k
    points by the counts of octants if that is less, bounds the tiles it then visits. Octants that are far longer along one
    axis make both bounds wide, so clouds of unequal extents want an index on a cubic grid. ``method``: batch (two phases
    over many centres at once) or bestfirst (one queue for each centre).

    ``fold``: what makes rows of the schema ``folded`` of many centres' whole lists, given the first entry of each centre
    and the carried columns end to end; those rows are the result. A centre's list in its home tile is folded there at once
    if no other tile comes within its k-th nearest, so only the other centres are searched a second time. No list is stored."""
    if not index.ordered and structure in LINEAR:
        raise ValueError("linear octrees need an index along a curve")
    spark, grid, curve, bucket = index.points.sparkSession, index.grid, index.curve if index.ordered else "morton", index.bucket
    # ranks along the curve count points, whatever the order of ``idx``, so bounds from counts hold for every index
    shared = spark.sparkContext.broadcast(TopTier(index.tiles, grid, curve))
    plain_index = Index(None, None, grid, index.curve, bucket)
    routing = "cid long, qx double, qy double, qz double, along long, bound double, tile int, chunk long"

    def route(home: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tier, chunks = shared.value, _Chunks()
            for b in batches:
                if not b.num_rows:
                    continue
                cid, q = b.column("cid").to_numpy(), _axes(b, ("qx", "qy", "qz"))
                if home:
                    bound = tier.descend(q, k)[1]
                    who, node = tier.within(q, np.zeros(len(q)))
                    who, first = np.unique(who, return_index=True)
                    tile = np.full(len(q), -1)  # a centre that lies in no tile
                    tile[who] = tier.tile[node[first]]
                    who = np.arange(len(q))
                else:
                    bound = b.column("bound").to_numpy()
                    who, node = tier.within(q, bound)
                    tile = tier.tile[node]
                along = _along(plain_index, q, cid).astype(np.int64)
                columns = (cid[who], q[who, 0], q[who, 1], q[who, 2], along[who], bound[who], tile.astype(np.int32), chunks.next(len(who)))
                yield pa.RecordBatch.from_arrays([*map(pa.array, columns)], names=[c.split()[0] for c in routing.split(", ")])

        return run

    def search(found: Callable[..., pa.Table]) -> Callable[[tuple, pa.Table, pa.Table], pa.Table]:
        def run(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
            tier, tile = shared.value, key[0].as_py()
            order = np.argsort(left.column("idx").to_numpy(), kind="stable")
            left = left.take(pa.array(order))
            xyz, codes, pid = _axes(left, ("x", "y", "z")), left.column("code").to_numpy(), left.column("pid").to_numpy()
            root = int(tier.tile_level[tile]), int(tier.tile_prefix[tile])
            box = node_boxes(np.array([root[0]]), np.array([root[1]]), grid, curve)
            tree = build_local(structure, xyz, codes, grid, curve, bucket, root, (box[0][0], box[1][0]), cell)
            right = right.take(pa.array(np.argsort(right.column("along").to_numpy(), kind="stable")))
            return found(tree, left, pid, right, right.column("cid").to_numpy(), _axes(right, ("qx", "qy", "qz")), right.column("bound").to_numpy())

        return run

    def tighten(tree: Walk, left: pa.Table, pid: np.ndarray, right: pa.Table, cid: np.ndarray, q: np.ndarray, bound: np.ndarray) -> pa.Table:
        return pa.table([*(right.column(c) for c in ("cid", "qx", "qy", "qz")), pa.array(tree.kth_batch(q, k, bound))], names=["cid", "qx", "qy", "qz", "bound"])

    def listed(tree: Walk, left: pa.Table, pid: np.ndarray, cid: np.ndarray, q: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """Which centres meet a point, the edges of their lists, and the lists' columns end to end."""
        rows = np.arange(len(pid))
        who, d2, item = (tree.knn_batch if method == "batch" else tree.knn_bestfirst)(q, k, pid, cid, bound.copy())
        order = np.argsort(who, kind="stable")
        who, d2, item = who[order], d2[order], item[order].astype(np.int64)
        by_pid = np.argsort(pid, kind="stable") if carry else rows
        spot = by_pid[np.searchsorted(pid[by_pid], item)] if carry else item
        values = [d2, item, *(left.column(c).to_numpy()[spot] for c in carry)]
        met, n = np.unique(who, return_counts=True)
        return met, np.concatenate(([0], np.cumsum(n))), values

    def nearest(tree: Walk, left: pa.Table, pid: np.ndarray, right: pa.Table, cid: np.ndarray, *asked: np.ndarray) -> pa.Table:
        met, edges, values = listed(tree, left, pid, cid, *asked)
        edges = pa.array(edges.astype(np.int32))
        return pa.table([pa.array(cid[met]), *(pa.ListArray.from_arrays(edges, pa.array(v)) for v in values)], names=["cid", "d2", "pid", *carry])

    def nearest_folded(tree: Walk, left: pa.Table, pid: np.ndarray, right: pa.Table, cid: np.ndarray, q: np.ndarray, bound: np.ndarray) -> pa.Table:
        """Rows of the lists of centres that visit no other tile, and those centres that do, with their bounds."""
        met, edges, values = listed(tree, left, pid, cid, q, bound)
        n, bound = np.diff(edges), bound.copy()
        bound[met[n == k]] = values[0][edges[1:][n == k] - 1]
        alone = np.bincount(shared.value.within(q, bound)[0], minlength=len(q)) == 1
        size, own = n[alone[met]], np.repeat(alone[met], n)
        rows = fold(np.cumsum(size) - size, [v[own] for v in values[2:]])
        others = pa.table([*(right.column(c) for c in ("cid", "qx", "qy", "qz")), pa.array(bound)], names=["cid", "qx", "qy", "qz", "bound"]).filter(pa.array(~alone))
        return pa.concat_tables([pa.Table.from_batches([rows]), others], promote_options="default")

    def put_together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.RecordBatch] = []
        for b in batches:
            if not b.num_rows:
                continue
            kept.append(b)
            cid = b.column("cid").to_numpy()
            whole = int(np.searchsorted(cid, cid[-1]))  # the last centre may go on in the next batch
            if whole:
                yield from _merge([*kept[:-1], b.slice(0, whole)], k)
                kept = [b.slice(whole)]
        if kept:
            yield from _merge(kept, k)

    routed = materialise(centres.select("cid", "qx", "qy", "qz").mapInArrow(route(True), routing), "at-home")
    points, asked = _dealt(index, routed.filter("tile >= 0"), () if fold is None else carry)
    placed = "cid long, qx double, qy double, qz double, bound double"
    both = points.groupBy("tile", "salt").cogroup(asked.groupBy("tile", "salt"))
    if fold is None:
        bounds = both.applyInArrow(search(tighten), placed)
    else:
        home = materialise(both.applyInArrow(search(nearest_folded), f"{folded}, {placed}"), "folded-at-home")
        bounds = home.filter("cid is not null").select("cid", "qx", "qy", "qz", "bound")
    bounds = bounds.unionByName(routed.filter("tile < 0").select(*bounds.columns))
    routed = materialise(bounds.mapInArrow(route(False), routing), "routed")
    points, asked = _dealt(index, routed, carry)
    lists = "cid long, d2 array<double>, pid array<bigint>" + "".join(f", {c} array<bigint>" for c in carry)
    near = points.groupBy("tile", "salt").cogroup(asked.groupBy("tile", "salt")).applyInArrow(search(nearest), lists)
    near = near.repartition("cid").sortWithinPartitions("cid")
    if fold is None:
        return near.mapInArrow(put_together, lists)

    def put_together_folded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in put_together(batches):
            yield fold(b.column("d2").offsets.to_numpy()[:-1], [b.column(c).flatten().to_numpy() for c in carry])

    return home.filter("cid is null").drop("cid", "qx", "qy", "qz", "bound").unionByName(near.mapInArrow(put_together_folded, folded))


def _merge(parts: list[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    """The k nearest of each centre from its lists of several tiles; rows come by centre."""
    t = pa.Table.from_batches(parts).combine_chunks()
    names = t.column_names[1:]
    lists = [t.column(c).combine_chunks() for c in names]
    lists = [x.chunk(0) if isinstance(x, pa.ChunkedArray) else x for x in lists]
    cid = np.repeat(t.column("cid").to_numpy(), lists[0].value_lengths().to_numpy())
    values = [x.flatten().to_numpy() for x in lists]
    d2, pid = values[0], values[1]
    order = np.lexsort((pid, pid != cid, d2, cid))
    cid = cid[order]
    first = np.flatnonzero(np.concatenate(([True], cid[1:] != cid[:-1]))) if len(cid) else NONE
    size = np.diff(np.append(first, len(cid)))
    top = np.arange(len(cid)) - np.repeat(first, size) < k
    edges = pa.array(np.concatenate(([0], np.cumsum(np.minimum(size, k)))).astype(np.int32))
    yield pa.RecordBatch.from_arrays([pa.array(cid[first]), *(pa.ListArray.from_arrays(edges, pa.array(v[order][top])) for v in values)], names=["cid", *names])


def knn_tiles(index: Index, centres: DataFrame, k: int, structure: str = "prune", cell: float = 0.0, method: str = "batch") -> DataFrame:
    """(cid, rank, pid, d2): the lists of ``knn_lists`` row by row."""
    found = knn_lists(index, centres, k, structure, cell, method).select("cid", F.posexplode(F.arrays_zip("pid", "d2")).alias("at", "s"))
    return found.select("cid", (F.col("at") + 1).cast("int").alias("rank"), "s.pid", "s.d2")


def top_k(pairs: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("cid").orderBy("d2", F.col("pid") != F.col("cid"), "pid")
    return pairs.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("cid", F.col("rank").cast("int").alias("rank"), "pid", "d2")


def output_bytes(found: DataFrame) -> DataFrame:
    """(n, entries, bytes) of all results: 16 bytes a range, 8 an index, 24 a point's coordinates."""
    size = next((b for c, b in (("ranges", 16), ("indices", 8), ("coords", 24)) if c in found.columns), 0)
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    return found.agg(total("n").alias("n"), total("n_ranges").alias("entries"), (total("n_ranges") * F.lit(size)).alias("bytes"))


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
