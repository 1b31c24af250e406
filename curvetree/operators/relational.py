"""Searches as plain DataFrame plans: brute force, the frontier walk over a node table, grid cover, and kNN by bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import GridSpec, quantise
from ..functions.kernels import Kernel, d2
from ..session import materialise, small
from .tiles import top_k



def _point() -> tuple[F.Column, ...]:
    return tuple(map(F.col, "xyz"))


def _centre() -> tuple[F.Column, ...]:
    return tuple(map(F.col, ("qx", "qy", "qz")))


def _packed(cx: F.Column, cy: F.Column, cz: F.Column) -> F.Column:
    """One join key from three cell numbers of up to 21 bits."""
    return F.shiftleft(cx.cast("long"), 42).bitwiseOR(F.shiftleft(cy.cast("long"), 21)).bitwiseOR(cz.cast("long"))


def radius_brute(points: DataFrame, centres: DataFrame, kernel: Kernel, r: float) -> DataFrame:
    """(cid, pid) by testing every pair: for small inputs, as a yardstick."""
    return points.join(F.broadcast(centres), kernel.hits(_point(), _centre(), F.lit(float(r)))).select("cid", "pid")


def summarise(pairs: DataFrame, centres: DataFrame) -> DataFrame:
    sums = pairs.groupBy("cid").agg(F.count("*").alias("n"), F.sum("pid").alias("pid_sum"))
    return centres.select("cid").join(sums, "cid", "left").select("cid", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("pid_sum", F.lit(0)).alias("pid_sum"))


def frontier_search(tree: DataFrame, centres: DataFrame, kernel: Kernel, r: float, mode: str = "prune", contain_leaves: bool = True) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(contained: cid, idx_lo, idx_hi; leaves to test: cid, qx.., level, prefix; visits: cid, nodes), level by level.

    ``tree`` holds boxes. Each round is one equi-join on (level, prefix) and a projection; rounds are stored, and there are
    at most as many as the tree is deep.
    """
    nodes = tree.filter("cnt > 0")
    lo, hi = tuple(map(F.col, ("x0", "y0", "z0"))), tuple(map(F.col, ("x1", "y1", "z1")))
    frontier = centres.select("cid", "qx", "qy", "qz", F.lit(0).alias("level"), F.lit(0).cast("long").alias("prefix"))
    seen = []
    while True:
        at = frontier.join(nodes, ["level", "prefix"]).withColumn("place", kernel.classify(lo, hi, _centre(), F.lit(float(r))))
        whole = (F.col("place") == "INSIDE") & F.lit(mode != "leafscan") & (F.lit(contain_leaves) | ~F.col("is_leaf"))
        step = F.when(F.col("place") == "OUTSIDE", "drop").when(whole, "take").when(F.col("is_leaf"), "test").otherwise("open")
        round_ = materialise(at.withColumn("step", step).select("cid", "qx", "qy", "qz", "level", "prefix", "cnt", "idx_lo", "idx_hi", "step"), "frontier")
        seen.append(round_)
        opened = round_.filter("step = 'open'")
        if opened.isEmpty():
            break
        frontier = opened.select("cid", "qx", "qy", "qz", (F.col("level") + 1).alias("level"), F.explode(F.expr("sequence(prefix * 8L, prefix * 8L + 7L)")).alias("prefix"))
    walked = seen[0]
    for s in seen[1:]:
        walked = walked.union(s)
    return walked.filter("step = 'take'").select("cid", "idx_lo", "idx_hi"), walked.filter("step = 'test'"), walked


def radius_frontier(tree: DataFrame, labelled: DataFrame, centres: DataFrame, kernel: Kernel, r: float, mode: str = "prune", chunk: int = 4096) -> DataFrame:
    """(cid, pid). ``labelled`` points carry idx and the (level, prefix) of their leaf."""
    take, test, _ = frontier_search(tree, centres, kernel, r, mode)
    tested = test.select("cid", "qx", "qy", "qz", "level", "prefix").join(labelled, ["level", "prefix"]).filter(kernel.hits(_point(), _centre(), F.lit(float(r)))).select("cid", "pid")
    cut = take.withColumn("c", F.explode(F.sequence(F.expr(f"idx_lo div {chunk}"), F.expr(f"(idx_hi - 1) div {chunk}"))))
    keyed = labelled.select("pid", "idx", F.expr(f"idx div {chunk}").alias("c"))
    bulk = cut.join(keyed, "c").filter((F.col("idx") >= F.col("idx_lo")) & (F.col("idx") < F.col("idx_hi"))).select("cid", "pid")
    return tested.union(bulk)


def label_points(ordered: DataFrame, tree: DataFrame, levels: int) -> DataFrame:
    """Each point with the level and prefix of its leaf: one equi-join for each level that has leaves, over what is left."""
    depths = [r[0] for r in tree.filter("is_leaf and cnt > 0").select("level").distinct().orderBy("level").collect()]  # 22 at most
    out, rest = None, ordered
    leaves = tree.filter("is_leaf and cnt > 0")
    for d in depths:
        here = leaves.filter(F.col("level") == d).select("level", "prefix")
        got = rest.withColumn("__p", F.shiftright("code", 3 * (levels - d))).join(here, F.col("__p") == F.col("prefix")).drop("__p")
        out = got if out is None else out.unionByName(got)
    return out


def radius_gridjoin(points: DataFrame, centres: DataFrame, kernel: Kernel, r: float, grid: GridSpec) -> DataFrame:
    """(cid, pid) through cells no narrower than r: 27 neighbour cells (9 for flat kernels) and an equi-join on the cell."""
    level = grid.levels
    while level > 0 and any(0 < e / 2**level < r for e in grid.ext[: kernel.dims]):
        level -= 1
    n = 1 << level
    coarse = GridSpec(grid.lo, grid.ext, level or 1, grid.box)
    if level == 0:
        return radius_brute(points, small(centres), kernel, r)
    axes = "xyz"[: kernel.dims]
    zero = F.lit(0)
    keyed = quantise(points, coarse).withColumn("cell", _packed(*(F.col(f"c{a}") if a in axes else zero for a in "xyz")))
    moved = centres.withColumns({a: F.col(f"q{a}") for a in "xyz"})
    wide = moved
    for i, a in enumerate("xyz"):
        if a in axes and grid.ext[i] > 0:
            # a centre outside the box still reaches its border cells
            at = F.floor((F.col(a) - F.lit(grid.lo[i])) / F.lit(grid.ext[i]) * F.lit(float(n))).cast("long")
            wide = wide.withColumn(f"c{a}", F.explode(F.sequence(at - 1, at + 1)))
            wide = wide.withColumn(f"c{a}", F.greatest(F.lit(0), F.least(F.lit(n - 1), F.col(f"c{a}"))).cast("int"))
        else:
            wide = wide.withColumn(f"c{a}", zero.cast("int"))
    cover = wide.select("cid", "qx", "qy", "qz", _packed(*(F.col(f"c{a}") for a in "xyz")).alias("cell")).distinct()
    return keyed.join(cover, "cell").filter(kernel.hits(_point(), _centre(), F.lit(float(r)))).select("cid", "pid")


def knn_brute(points: DataFrame, centres: DataFrame, k: int) -> DataFrame:
    pairs = points.crossJoin(F.broadcast(centres)).select("cid", "pid", d2(_point(), _centre()).alias("d2"))
    return top_k(pairs, k)


def knn_relational(points: DataFrame, centres: DataFrame, k: int, grid: GridSpec, level: int | None = None) -> DataFrame:
    """(cid, rank, pid, d2): a radius that surely holds k points, from counts of the cells around each centre; then a cell cover and top-k.

    Cells are cubes, whatever ``grid``'s extents. Centres walk up from ``level`` to the first octant around them with k
    points; its farthest corner bounds the distance. By default the level follows the cloud, so that a cell with points
    holds about 2 k of them on average. The ball is covered by at most 27 octants about as wide as it, whatever its size;
    of those only the cells that hold points and come within the bound are joined with points.
    """
    from ..functions.curves import encode

    wide = max(grid.ext) or 1.0
    cubes = GridSpec(grid.lo, (wide,) * 3, grid.levels, "cubic")
    coded = encode(points, cubes, "morton")
    if level is None:
        kinds = [F.approx_count_distinct(F.shiftright("code", 3 * (grid.levels - lv))).alias(f"l{lv}") for lv in range(grid.levels + 1)]
        total, *cells = coded.agg(F.count("*"), *kinds).first()
        level = max([0, *(lv for lv, n in enumerate(cells) if total >= 2 * k * n)])
    own = [F.shiftright(f"c{a}", grid.levels - level).alias(f"k{a}") for a in "xyz"]
    filled = materialise(coded.groupBy(*own).agg(F.count("*").alias("cnt")).withColumn("cell", _packed(*(F.col(f"k{a}") for a in "xyz"))), "filled-cells")
    above = filled.select("*", F.explode(F.sequence(F.lit(0), F.lit(level))).alias("lv")).withColumn("octant", _packed(*(F.expr(f"shiftright(k{a}, {level} - lv)") for a in "xyz")))
    counts = above.groupBy("lv", "octant").agg(F.sum("cnt").alias("cnt"))
    at = encode(centres.withColumns({a: F.col(f"q{a}") for a in "xyz"}), cubes, "morton")
    up = at.select("cid", "qx", "qy", "qz", "cx", "cy", "cz", F.explode(F.sequence(F.lit(level), F.lit(0), F.lit(-1))).alias("lv"))
    up = up.withColumn("octant", _packed(*(F.expr(f"shiftright(c{a}, {grid.levels} - lv)") for a in "xyz"))).join(counts, ["lv", "octant"]).filter((F.col("cnt") >= k) | (F.col("lv") == 0))
    far, side = F.lit(0.0), F.lit(wide) / F.pow(F.lit(2.0), "lv")
    for i, a in enumerate("xyz"):
        lo = F.lit(grid.lo[i]) + F.expr(f"shiftright(c{a}, {grid.levels} - lv)") * side
        gap = F.greatest(F.abs(F.col(f"q{a}") - lo), F.abs(lo + side - F.col(f"q{a}")))
        far = far + gap * gap
    # an octant without k points bounds nothing: all points are then within reach of the root's farthest corner
    bound = up.withColumn("far", far * (1 + 1e-9)).groupBy("cid", "qx", "qy", "qz").agg(F.max_by("far", "lv").alias("bound"))
    pad = F.lit(wide * 1e-12)  # cells are found by other roundings than distances
    reach = F.sqrt("bound") * (1 + 1e-9) + pad
    ball = bound.withColumn("lv", F.greatest(F.lit(0), F.least(F.lit(level), F.floor(F.log2(F.lit(wide) / reach)))).cast("int"))
    most = F.expr("shiftleft(1, lv) - 1")
    for i, a in enumerate("xyz"):
        to = lambda v, i=i: F.greatest(F.lit(0), F.least(most, F.floor((v - F.lit(grid.lo[i])) / side)))
        ball = ball.withColumn(f"o{a}", F.explode(F.sequence(to(F.col(f"q{a}") - reach), to(F.col(f"q{a}") + reach))))
    ball = ball.withColumn("octant", _packed(*(F.col(f"o{a}") for a in "xyz")))
    away, width = F.lit(0.0), wide / 2**level
    for i, a in enumerate("xyz"):
        lo = F.lit(grid.lo[i]) + F.col(f"k{a}") * F.lit(width)
        gap = F.greatest(lo - pad - F.col(f"q{a}"), F.col(f"q{a}") - (lo + F.lit(width) + pad), F.lit(0.0))
        # a point beyond a frozen grid lies in its border cell
        away = away + F.when((F.col(f"k{a}") == 0) | (F.col(f"k{a}") == 2**level - 1), 0.0).otherwise(gap * gap)
    cover = ball.join(above.drop("cnt"), ["lv", "octant"]).filter(away <= F.col("bound")).select("cid", "qx", "qy", "qz", "bound", "cell")
    near = coded.select("pid", "x", "y", "z", _packed(*own).alias("cell")).join(cover, "cell")
    pairs = near.select("cid", "pid", d2(_point(), _centre()).alias("d2"), "bound").filter("d2 <= bound").select("cid", "pid", "d2")
    return top_k(pairs, k)
