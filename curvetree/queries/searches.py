"""Fixed-radius and nearest-neighbour searches, locality, and work counters.

Centres are all points whose id is divisible by 100, at every size of the tables; the queries named ``full`` take all points.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import GridSpec, as_cubic, fit_grid
from ..functions.kernels import KERNELS, SPHERE
from ..operators import costs, features, locality, relational, tiles
from ..operators.octree import build_tree, with_boxes
from ..operators.reorder import Index, build_index
from ..sources import clouds
from . import sqltext as s

# few points to a leaf and a large radius, so that octants are contained and the shortcut is exercised
CLOUD, RADIUS, BUCKET, TILE_POINTS, K, FULL_RADIUS = "event", 200.0, 16, 2000, 20, 50.0
_INDEXES: dict[tuple, Index] = {}
_GRIDS: dict[tuple, GridSpec] = {}


def index_of(spark: SparkSession, d: str, name: str = CLOUD, curve: str = "hilbert", bucket: int = BUCKET, tile_points: int = TILE_POINTS, box: str = "axis") -> Index:
    """The index of a cloud; built once a session, as its tables are stored. Nearest neighbours are searched on a ``cubic``
    grid: octants as long as they are wide give tight bounds, whatever the extents of the axes."""
    key = (spark.sparkContext.applicationId, d, name, curve, bucket, tile_points, box)
    if key not in _INDEXES:
        cloud, grid = clouds.load(spark, d, name), grid_of(spark, d, name)
        total = cloud.count()
        # tiles grow with the cloud, to a size that a task searches as a whole: each costs a task the same few milliseconds
        tile_points = max(tile_points, min(total // 64, 50_000))
        _INDEXES[key] = build_index(cloud, curve, bucket, tile_points, as_cubic(grid) if box == "cubic" else grid, total)
    return _INDEXES[key]


def grid_of(spark: SparkSession, d: str, name: str = CLOUD) -> GridSpec:
    """The grid of a cloud's bounding box, fitted once a session like its indexes."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _GRIDS:
        _GRIDS[key] = fit_grid(clouds.load(spark, d, name))
    return _GRIDS[key]


def indexed(spark: SparkSession, d: str, curve: str = "hilbert", name: str = CLOUD, box: str = "axis") -> tuple[Index, DataFrame]:
    return index_of(spark, d, name, curve, box=box), clouds.id_centres(clouds.load(spark, d, name))


def by_tiles(kernel: str, structure: str, curve: str, spark: SparkSession, d: str) -> DataFrame:
    index, q = indexed(spark, d, curve)
    return tiles.radius_summary(index, q, tiles.radius_tiles(index, q, KERNELS[kernel], RADIUS, structure, cell=40.0))


def full_search(structure: str, spark: SparkSession, d: str) -> DataFrame:
    """Every point a centre, in the order of the index."""
    index = index_of(spark, d)
    q = clouds.all_centres(index.points)
    return tiles.radius_summary(index, q, tiles.radius_tiles(index, q, SPHERE, FULL_RADIUS, structure))


def _labelled(spark: SparkSession, d: str, name: str = CLOUD) -> tuple[DataFrame, DataFrame, DataFrame, Index]:
    index, q = indexed(spark, d, name=name)
    tree = with_boxes(build_tree(index.points, BUCKET, 21), index.grid, index.curve)
    return tree, relational.label_points(index.points, tree, 21), q, index


def by_frontier(mode: str, spark: SparkSession, d: str) -> DataFrame:
    tree, points, q, _ = _labelled(spark, d)
    return relational.summarise(relational.radius_frontier(tree, points, q, SPHERE, RADIUS, mode), q)


def by_grid(kernel: str, spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, CLOUD)
    q = clouds.id_centres(p)
    return relational.summarise(relational.radius_gridjoin(p, q, KERNELS[kernel], RADIUS, fit_grid(p)), q)


def pairs(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return relational.radius_gridjoin(p, clouds.id_centres(p), SPHERE, 100.0, fit_grid(p))


def expanded(spark: SparkSession, d: str) -> DataFrame:
    index, q = indexed(spark, d, name="order")
    return tiles.expand_ranges(tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, 100.0), q), index.points)


def range_sums(spark: SparkSession, d: str) -> DataFrame:
    index, q = indexed(spark, d)
    return tiles.aggregate_ranges(tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, RADIUS)), index.points, "pid", 512).select("cid", "n", F.col("total").alias("pid_sum"))


def per_centre_radius(spark: SparkSession, d: str) -> DataFrame:
    index, q = indexed(spark, d)
    own = q.withColumn("r", F.lit(50.0) + F.col("cid") % 5 * F.lit(50.0))
    return tiles.radius_summary(index, q, tiles.radius_tiles(index, own, SPHERE, None))


def index_lists(spark: SparkSession, d: str) -> DataFrame:
    """The pruning search's own result: every neighbour's index, one by one."""
    index, q = indexed(spark, d)
    found = tiles.merge_lists(tiles.radius_tiles(index, q, SPHERE, RADIUS, "prune"), q)
    return found.select("cid", F.explode("indices").alias("idx"))


def range_lists(spark: SparkSession, d: str) -> DataFrame:
    """The range search's own result: every maximal range of neighbours' indices."""
    index, q = indexed(spark, d)
    found = tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, RADIUS, "ranges"), q)
    return found.select("cid", F.explode("ranges").alias("s")).select("cid", "s.lo", "s.hi")


def coordinate_lists(spark: SparkSession, d: str) -> DataFrame:
    """The non-complete octree's result: every neighbour's coordinates, summed up."""
    index, q = indexed(spark, d)
    found = tiles.merge_lists(tiles.radius_tiles(index, q, SPHERE, RADIUS, "noncomplete"), q).select("cid", F.explode("coords").alias("c"))
    return found.groupBy("cid").agg(F.count("*").alias("n"), *(F.round(F.sum(f"c.{a}"), 3).alias(f"s{a}") for a in "xyz"))


def output_sizes(spark: SparkSession, d: str) -> DataFrame:
    """(form, n, entries, bytes) of the same search's result as ranges, indices and coordinates."""
    index, q = indexed(spark, d)
    out = []
    for form, structure in (("ranges", "ranges"), ("indices", "prune"), ("coords", "noncomplete")):
        found = tiles.radius_tiles(index, q, SPHERE, RADIUS, structure)
        merged = tiles.merge_ranges(found) if form == "ranges" else tiles.merge_lists(found)
        size = {"ranges": 16, "indices": 8, "coords": 24}[form]
        entries = F.coalesce(F.sum(F.size(form)), F.lit(0)).cast("long")
        out.append(merged.agg(F.sum("n").cast("long").alias("n"), entries.alias("entries"), (entries * size).alias("bytes")).select(F.lit(form).alias("form"), "*"))
    return tiles.union_all(out)


def neighbour_options(spark: SparkSession, d: str) -> DataFrame:
    """Neighbours other than the point itself, for centres that have at least 20 of them."""
    index, q = indexed(spark, d)
    return tiles.neighbours(index, q, SPHERE, 100.0, exclude_self=True, min_count=20).select("cid", "n", F.size("ranges").cast("long").alias("n_ranges"))


def knn(structure: str, method: str, spark: SparkSession, d: str) -> DataFrame:
    index, _ = indexed(spark, d, box="cubic")
    return tiles.knn_tiles(index, clouds.id_centres(index.points), K, structure, cell=40.0, method=method).select("cid", "rank", "pid")


def knn_full(spark: SparkSession, d: str) -> DataFrame:
    index = index_of(spark, d, "part", box="cubic")
    return tiles.knn_tiles(index, clouds.all_centres(index.points), K).select("cid", "rank", "pid")


def knn_unordered(spark: SparkSession, d: str) -> DataFrame:
    index, q = indexed(spark, d, "none", box="cubic")
    return tiles.knn_tiles(index, q, K, "pointer").select("cid", "rank", "pid")


def knn_by_bounds(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, CLOUD)
    return relational.knn_relational(p, clouds.id_centres(p), K, fit_grid(p)).select("cid", "rank", "pid")


def counters(spark: SparkSession, d: str) -> DataFrame:
    """Work of the pruning search on the whole tree as one tile: what the frontier of joins visits, takes and tests."""
    tree, _, q, _ = _labelled(spark, d)
    _, _, walked = relational.frontier_search(tree, q, SPHERE, RADIUS)
    n = lambda step, what: F.sum(F.when(F.col("step") == step, what).otherwise(0)).cast("long")
    return walked.groupBy("cid").agg(F.count("*").alias("nodes"), n("take", 1).alias("contained"), n("test", 1).alias("leaves"), n("test", F.col("cnt")).alias("tested"), n("take", F.col("cnt")).alias("bulk"))


def counters_by_arrays(spark: SparkSession, d: str) -> DataFrame:
    index, q = index_of(spark, d, tile_points=10**9), clouds.id_centres(clouds.load(spark, d, CLOUD))
    return tiles.work_counters(tiles.radius_tiles(index, q, SPHERE, RADIUS, "prune")).select("cid", "nodes", "contained", "leaves", "tested", "bulk")


def mu(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, CLOUD)
    q, grid = clouds.id_centres(p), fit_grid(p)
    return tiles.union_all([costs.mean_neighbours(relational.summarise(relational.radius_gridjoin(p, q, kernel, 50.0, grid), q)).select(F.lit(name).alias("kernel"), "mu", "centres") for name, kernel in KERNELS.items()])


def _lists(spark: SparkSession, d: str, name: str = "part", share: float = 1.0, k: int = 50, curves: tuple[str, ...] = ("none", "morton", "hilbert")) -> DataFrame:
    p = clouds.load(spark, d, name)
    index = index_of(spark, d, name, bucket=32, box="cubic")
    return locality.neighbour_ranks(index, p, clouds.share_of_centres(index.points, share), k, fit_grid(p), curves)


def _gaps(spark: SparkSession, d: str, name: str = "part", share: float = 1.0, k: int = 50, curves: tuple[str, ...] = ("none", "morton", "hilbert")) -> DataFrame:
    index = index_of(spark, d, name, bucket=32, box="cubic")
    return locality.neighbour_gaps(index, clouds.load(spark, d, name), clouds.share_of_centres(index.points, share), k, grid_of(spark, d, name), curves)


def histogram(curve: str, spark: SparkSession, d: str) -> DataFrame:
    return locality.histogram(_gaps(spark, d, curves=(curve,)))


def histogram_without_self(spark: SparkSession, d: str) -> DataFrame:
    return locality.histogram(_gaps(spark, d, curves=("hilbert",)), include_self=False)


def multiplicity(spark: SparkSession, d: str) -> DataFrame:
    """How many centres have one, and how many two, neighbours at a gap."""
    return _gaps(spark, d, curves=("hilbert",)).select("d", "n", F.col("h").alias("centres"))


def quartiles(spark: SparkSession, d: str) -> DataFrame:
    return locality.quartiles(locality.histogram(_gaps(spark, d)))


def skewness(spark: SparkSession, d: str) -> DataFrame:
    return locality.skewness(locality.histogram(_gaps(spark, d)))


def sampled(spark: SparkSession, d: str) -> DataFrame:
    return locality.skewness(locality.histogram(_gaps(spark, d, "event", 0.1)))


def choice(spark: SparkSession, d: str) -> DataFrame:
    """The ordering that a tenth of the centres recommends, for each of two clouds."""
    out = []
    for name in ("part", "embed"):
        best = locality.skewness(locality.histogram(_gaps(spark, d, name, 0.1))).orderBy(F.desc("g1"), "curve").limit(1)
        out.append(best.select(F.lit(name).alias("cloud"), "curve"))
    return tiles.union_all(out)


def binned(spark: SparkSession, d: str) -> DataFrame:
    return locality.log_bins(locality.histogram(_gaps(spark, d)))


def invariants(spark: SparkSession, d: str) -> DataFrame:
    n = clouds.load(spark, d, "part").count()
    return locality.check_histogram(locality.histogram(_gaps(spark, d)), n, 50)


def blocks(spark: SparkSession, d: str) -> DataFrame:
    return locality.blocks_touched(_lists(spark, d), 2)


def lru(spark: SparkSession, d: str) -> DataFrame:
    return locality.lru_misses(locality.list_gaps(_lists(spark, d)), 64)


def density(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return features.density(p, fit_grid(p), SPHERE, 50.0).select("cid", "n", F.round("density", 12).alias("density"))


def isolated(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return features.isolated_points(p, fit_grid(p), 25.0)


def _order_moments(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return features.local_moments(relational.radius_gridjoin(p, clouds.id_centres(p), SPHERE, 100.0, fit_grid(p)), p)


def moments(spark: SparkSession, d: str) -> DataFrame:
    m = _order_moments(spark, d)
    return m.select("cid", "n", *(F.round(F.col(c) + F.lit(1e-7), 4).alias(c) for c in m.columns[2:]))


def shapes(spark: SparkSession, d: str) -> DataFrame:
    return features.shape(_order_moments(spark, d))


def components(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "embed")
    return features.radius_components(p, fit_grid(p), 60.0)


def shared(spark: SparkSession, d: str) -> DataFrame:
    p, index = clouds.load(spark, d, "part"), index_of(spark, d, "part", bucket=32, box="cubic")
    found = tiles.knn_tiles(index, clouds.all_centres(p), 10)
    ranked = locality.ranks(p, fit_grid(p), ("morton",)).select("pid", "idx")
    return features.shared_neighbours(found.select("cid", "pid"), ranked)


def rollup(spark: SparkSession, d: str) -> DataFrame:
    """Points of each octant of the first three levels, by one rollup over octal digits."""
    p = clouds.load(spark, d, "order")
    digit = lambda i: (F.shiftright("code", 63 - 3 * i).bitwiseAND(F.lit(7))).cast("int").alias(f"d{i}")
    coded = encode(p, fit_grid(p), "morton").select(digit(1), digit(2), digit(3))
    return coded.rollup("d1", "d2", "d3").agg(F.count("*").alias("cnt"))


def leaf_members(spark: SparkSession, d: str) -> DataFrame:
    """The ids of each leaf's points in the order of the curve: a sort aggregation."""
    tree, points, _, _ = _labelled(spark, d)
    held = points.groupBy("level", "prefix").agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "pid"))), lambda s_: s_["pid"]).alias("ids"))
    return held.select("level", "prefix", F.size("ids").cast("long").alias("cnt"), F.array_join(F.transform("ids", lambda i: i.cast("string")), ",").alias("ids"))


STRUCTURES = {"pointer": "pointer", "leafscan": "leafscan", "prune": "prune", "ranges": "ranges"}
QUERIES = {
    **{f"radius_{k}_{n}": partial(by_tiles, k, st, "hilbert") for k in KERNELS for n, st in STRUCTURES.items()},
    **{f"radius_full_{n}": partial(full_search, st) for n, st in STRUCTURES.items()},
    "radius_sphere_pointer_none": partial(by_tiles, "sphere", "pointer", "none"),
    "radius_sphere_pointer_morton": partial(by_tiles, "sphere", "pointer", "morton"),
    "radius_sphere_ranges_morton": partial(by_tiles, "sphere", "ranges", "morton"),
    "radius_noncomplete": partial(by_tiles, "sphere", "noncomplete", "hilbert"),
    "radius_resolution": partial(by_tiles, "sphere", "resolution", "hilbert"),
    "radius_kdtree_small": partial(by_tiles, "sphere", "kd_small", "hilbert"),
    "radius_kdtree": partial(by_tiles, "sphere", "kd_ten", "hilbert"),
    "radius_kdtree_sliding": partial(by_tiles, "cube", "kd_sliding", "hilbert"),
    "radius_kdtree_none": partial(by_tiles, "sphere", "kd_ten", "none"),
    "radius_frontier_leafscan": partial(by_frontier, "leafscan"),
    "radius_frontier_prune": partial(by_frontier, "prune"),
    "radius_gridjoin": partial(by_grid, "sphere"),
    "radius_gridjoin_square": partial(by_grid, "square"),
    "radius_pairs_sphere": pairs,
    "radius_range_expand": expanded,
    "radius_range_sums": range_sums,
    "radius_per_centre": per_centre_radius,
    "radius_index_lists": index_lists,
    "radius_range_lists": range_lists,
    "radius_coordinate_lists": coordinate_lists,
    "radius_output_sizes": output_sizes,
    "radius_neighbour_options": neighbour_options,
    "knn_bestfirst": partial(knn, "prune", "bestfirst"),
    "knn_two_phase": partial(knn, "prune", "batch"),
    "knn_full": knn_full,
    "knn_pointer": partial(knn, "pointer", "bestfirst"),
    "knn_pointer_none": knn_unordered,
    "knn_resolution": partial(knn, "resolution", "batch"),
    "knn_kdtree": partial(knn, "kd_ten", "batch"),
    "knn_kdtree_small": partial(knn, "kd_small", "batch"),
    "knn_kdtree_sliding": partial(knn, "kd_sliding", "bestfirst"),
    "knn_relational": knn_by_bounds,
    "search_work_counters": counters,
    "search_work_counters_arrays": counters_by_arrays,
    "mean_neighbours": mu,
    **{f"locality_hist_{c}": partial(histogram, c) for c in ("none", "morton", "hilbert")},
    "locality_hist_without_self": histogram_without_self,
    "locality_gap_multiplicity": multiplicity,
    "locality_quartiles": quartiles,
    "locality_skewness": skewness,
    "locality_sampled": sampled,
    "locality_bins": binned,
    "locality_invariants": invariants,
    "curve_choice": choice,
    "blocks_touched": blocks,
    "lru_misses": lru,
    "density": density,
    "isolated_points": isolated,
    "local_moments": moments,
    "local_shape": shapes,
    "radius_components": components,
    "shared_neighbours": shared,
    "octant_rollup": rollup,
    "leaf_members": leaf_members,
}

_SPHERE = s.radius(CLOUD, "sphere", RADIUS)
_KNN = f"WITH p AS ({s.CLOUD[CLOUD]}), {s.by_id()}, {s.knn(K)} SELECT cid, rank::INT AS rank, pid FROM n"


def _hist(name: str, curves: tuple[str, ...], share: float | None = None, k: int = 50) -> str:
    """Query text giving (curve, d, h), one subquery a curve."""
    parts = []
    for c in curves:
        rank = "row_number() OVER (ORDER BY pid) - 1" if c == "none" else "idx"
        q = s.share(share or 1.0)
        parts.append(f"SELECT '{c}' AS curve, d, count(*) AS h FROM (WITH RECURSIVE {s.coded(name, c)}, o AS (SELECT pid, {rank} AS pos FROM k), {q}, {s.knn(k)} SELECT abs(a.pos - b.pos) AS d FROM n JOIN o a ON a.pid = n.cid JOIN o b ON b.pid = n.pid) {c}_ GROUP BY d")
    return " UNION ALL ".join(parts)


_ALL = ("none", "morton", "hilbert")


def _skew(name: str, share: float | None = None) -> str:
    return f"""WITH m AS (SELECT curve, sum(h)::BIGINT AS n_pairs, sum(d::HUGEINT * h)::DOUBLE AS s1, sum(d::HUGEINT * d * h)::DOUBLE AS s2, sum(d::HUGEINT * d * d * h)::DOUBLE AS s3 FROM ({_hist(name, _ALL, share)}) GROUP BY curve),
v AS (SELECT *, s1 / n_pairs AS mean, s2 / n_pairs - (s1 / n_pairs) * (s1 / n_pairs) AS var FROM m)
SELECT curve, n_pairs, round((s3 / n_pairs - 3.0::DOUBLE * mean * s2 / n_pairs + 2.0::DOUBLE * mean * mean * mean) / (var * sqrt(var)), 6) AS g1 FROM v"""


def _gap_rows(name: str) -> str:
    parts = []
    for c in _ALL:
        rank = "row_number() OVER (ORDER BY pid) - 1" if c == "none" else "idx"
        parts.append(f"SELECT '{c}' AS curve, cid, pos FROM (WITH RECURSIVE {s.coded(name, c)}, o AS (SELECT pid, {rank} AS pos FROM k), {s.share(1.0)}, {s.knn(50)} SELECT n.cid, o.pos FROM n JOIN o ON o.pid = n.pid) {c}_")
    return " UNION ALL ".join(parts)


_ORDER = f"WITH p AS ({s.CLOUD['order']})"
_ORDER_ALL = f"{_ORDER}, q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM p)"
_ORDER_Q = f"{_ORDER}, {s.by_id()}"
#: CTEs up to hits (cid, pid, idx, x, y, z): neighbours with their ranks along the Hilbert curve
_HITS = f"WITH RECURSIVE {s.coded(CLOUD, 'hilbert')}, {s.by_id()}, hits AS (SELECT cid, pid, idx, x, y, z FROM q, k WHERE {s.hit('sphere', RADIUS)})"
_ISLANDS = "SELECT cid, min(idx) AS lo, max(idx) + 1 AS hi FROM (SELECT cid, idx, idx - row_number() OVER (PARTITION BY cid ORDER BY idx) AS g FROM {0}) x GROUP BY cid, g"
_COUNTERS = f"""{s.classified(CLOUD, 'hilbert', BUCKET, RADIUS)} SELECT cid, count(*) AS nodes, count(*) FILTER (WHERE place = 1) AS contained, count(*) FILTER (WHERE place = 0 AND is_leaf) AS leaves,
  coalesce(sum(cnt) FILTER (WHERE place = 0 AND is_leaf), 0)::BIGINT AS tested, coalesce(sum(cnt) FILTER (WHERE place = 1), 0)::BIGINT AS bulk FROM walked GROUP BY cid"""
ORACLE = {
    **{f"radius_{k}_{n}": s.radius(CLOUD, k, RADIUS) for k in KERNELS for n in STRUCTURES},
    **{f"radius_full_{n}": s.radius(CLOUD, "sphere", FULL_RADIUS, step=1) for n in STRUCTURES},
    **{k: _SPHERE for k in ("radius_sphere_pointer_none", "radius_sphere_pointer_morton", "radius_sphere_ranges_morton", "radius_noncomplete", "radius_resolution", "radius_kdtree_small", "radius_kdtree", "radius_kdtree_none", "radius_frontier_leafscan", "radius_frontier_prune", "radius_gridjoin")},
    "radius_kdtree_sliding": s.radius(CLOUD, "cube", RADIUS),
    "radius_gridjoin_square": s.radius(CLOUD, "square", RADIUS),
    **{k: f"{_ORDER_Q} SELECT cid, pid FROM q, p WHERE {s.hit('sphere', 100.0)}" for k in ("radius_pairs_sphere", "radius_range_expand")},
    "radius_range_sums": f"SELECT * FROM ({_SPHERE}) x WHERE n > 0",
    "radius_per_centre": f"WITH p AS ({s.CLOUD[CLOUD]}), {s.by_id()} SELECT q.cid, count(p.pid) AS n, coalesce(sum(p.pid), 0)::BIGINT AS pid_sum FROM q LEFT JOIN p ON {s.D2} < (50.0::DOUBLE + cid % 5 * 50.0::DOUBLE) * (50.0::DOUBLE + cid % 5 * 50.0::DOUBLE) GROUP BY q.cid",
    "radius_index_lists": f"{_HITS} SELECT cid, idx FROM hits",
    "radius_range_lists": f"{_HITS} {_ISLANDS.format('hits')}",
    "radius_coordinate_lists": f"{_HITS} SELECT cid, count(*) AS n, round(sum(x), 3) AS sx, round(sum(y), 3) AS sy, round(sum(z), 3) AS sz FROM hits GROUP BY cid",
    "radius_output_sizes": f"{_HITS}, i AS ({_ISLANDS.format('hits')}), sums AS (SELECT (SELECT count(*) FROM hits) AS n, (SELECT count(*) FROM i) AS r) SELECT 'ranges' AS form, n, r AS entries, r * 16 AS bytes FROM sums UNION ALL SELECT 'indices', n, n, n * 8 FROM sums UNION ALL SELECT 'coords', n, n, n * 24 FROM sums",
    "radius_neighbour_options": f"WITH RECURSIVE {s.coded(CLOUD, 'hilbert')}, {s.by_id()}, hits AS (SELECT cid, idx FROM q, k WHERE pid <> cid AND {s.hit('sphere', 100.0)}), i AS ({_ISLANDS.format('hits')}) SELECT cid, sum(hi - lo)::BIGINT AS n, count(*) AS n_ranges FROM i GROUP BY cid HAVING sum(hi - lo) >= 20",
    **{k: _KNN for k in ("knn_bestfirst", "knn_two_phase", "knn_pointer", "knn_pointer_none", "knn_resolution", "knn_kdtree", "knn_kdtree_small", "knn_kdtree_sliding", "knn_relational")},
    "knn_full": f"WITH p AS ({s.CLOUD['part']}), {s.by_id(1)}, {s.knn(K)} SELECT cid, rank::INT AS rank, pid FROM n",
    **{k: _COUNTERS for k in ("search_work_counters", "search_work_counters_arrays")},
    "mean_neighbours": " UNION ALL ".join(f"SELECT '{k}' AS kernel, round(sum(n)::DOUBLE / count(*), 6) AS mu, count(*) AS centres FROM ({s.radius(CLOUD, k, 50.0)}) {k}_" for k in KERNELS),
    **{f"locality_hist_{c}": _hist("part", (c,)) for c in _ALL},
    "locality_hist_without_self": f"SELECT * FROM ({_hist('part', ('hilbert',))}) x WHERE d > 0",
    "locality_gap_multiplicity": f"SELECT d, n, count(*) AS centres FROM (WITH RECURSIVE {s.coded('part', 'hilbert')}, {s.share(1.0)}, {s.knn(50)} SELECT a.idx AS i, abs(a.idx - b.idx) AS d, count(*) AS n FROM n JOIN k a ON a.pid = n.cid JOIN k b ON b.pid = n.pid GROUP BY 1, 2) x GROUP BY d, n",
    "locality_quartiles": f"WITH h AS ({_hist('part', _ALL)}), c AS (SELECT *, sum(h) OVER (PARTITION BY curve ORDER BY d) AS c, sum(h) OVER (PARTITION BY curve) AS n FROM h) SELECT curve, " + ", ".join(f"min(CASE WHEN c >= ceil({p}::DOUBLE * n) THEN d END) AS q{i}" for i, p in ((1, 0.25), (2, 0.5), (3, 0.75))) + " FROM c GROUP BY curve",
    "locality_skewness": _skew("part"),
    "locality_sampled": _skew("event", 0.1),
    "locality_bins": f"SELECT curve, (CASE WHEN d = 0 THEN -1 ELSE floor(log2(d)) END)::INT AS bin, sum(h)::BIGINT AS h FROM ({_hist('part', _ALL)}) x GROUP BY 1, 2",
    "locality_invariants": f"SELECT curve, sum(CASE WHEN d = 0 THEN h ELSE 0 END) = (SELECT count(*) FROM part) AND sum(h) = (SELECT count(*) * least(50, count(*)) FROM part) AS ok FROM ({_hist('part', _ALL)}) x GROUP BY curve",
    "curve_choice": " UNION ALL ".join(f"SELECT * FROM (SELECT '{n}' AS cloud, curve FROM ({_skew(n, 0.1)}) a{n} ORDER BY g1 DESC, curve LIMIT 1) b{n}" for n in ("part", "embed")),
    "blocks_touched": f"SELECT curve, round(avg(b), 6) AS blocks FROM (SELECT curve, cid, count(DISTINCT pos // 2) AS b FROM ({_gap_rows('part')}) x GROUP BY curve, cid) y GROUP BY curve",
    "density": f"{_ORDER_ALL} SELECT cid, count(*) AS n, round(count(*) / {4 / 3 * 3.141592653589793 * 50.0**3!r}::DOUBLE, 12) AS density FROM q JOIN p ON {s.hit('sphere', 50.0)} GROUP BY cid",
    "isolated_points": f"{_ORDER_ALL} SELECT pid FROM p WHERE pid NOT IN (SELECT cid FROM q, p WHERE cid <> pid AND {s.hit('sphere', 25.0)})",
    "local_moments": f"{_ORDER_Q} SELECT cid, count(*) AS n, " + ", ".join(f"round(avg({a}) + 0.0000001::DOUBLE, 4) AS m{a}" for a in "xyz") + ", " + ", ".join(f"round(covar_pop({a}, {b}) + 0.0000001::DOUBLE, 4) AS c{a}{b}" for i, a in enumerate("xyz") for b in "xyz"[i:]) + f" FROM q JOIN p ON {s.hit('sphere', 100.0)} GROUP BY cid",
    "radius_components": f"WITH RECURSIVE p AS ({s.CLOUD['embed']}), q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM p), e AS (SELECT cid, pid FROM q, p WHERE cid <> pid AND {s.hit('sphere', 60.0)}), w AS (SELECT pid AS start, pid AS pos FROM p UNION SELECT w.start, e.pid FROM w JOIN e ON e.cid = w.pos) SELECT pos AS pid, min(start) AS component FROM w GROUP BY pos",
    "shared_neighbours": f"WITH RECURSIVE {s.coded('part', 'morton')}, q AS (SELECT pid AS cid, x AS qx, y AS qy, z AS qz FROM p), {s.knn(10)}, a AS (SELECT k.idx AS i, n.pid FROM n JOIN k ON k.pid = n.cid) SELECT a.i, count(*) AS shared FROM a JOIN a b ON b.i = a.i + 1 AND b.pid = a.pid GROUP BY a.i",
    "octant_rollup": f"WITH {s.coded('order', 'morton')}, o AS (SELECT ((code >> 60) & 7)::INT AS d1, ((code >> 57) & 7)::INT AS d2, ((code >> 54) & 7)::INT AS d3 FROM k) SELECT d1, d2, d3, count(*) AS cnt FROM o GROUP BY ROLLUP (d1, d2, d3)",
    "leaf_members": f"WITH RECURSIVE {s.tree(CLOUD, 'hilbert', BUCKET)} SELECT t.level, t.prefix, count(*) AS cnt, string_agg(k.pid::VARCHAR, ',' ORDER BY k.idx) AS ids FROM t JOIN k ON k.idx >= t.idx_lo AND k.idx < t.idx_hi WHERE t.is_leaf GROUP BY t.level, t.prefix",
}
