"""The operators a user needs around the searches: scans, joins, aggregates, windows, sets and functions on the given tables.

Queries whose text is one in both dialects are written once; ``{table}`` stands for a table. The others are DataFrame code
with their own SQL twin.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import fit_grid
from ..functions.kernels import KERNELS, SPHERE
from ..functions.registered import range_union, register, register_knn
from ..operators import relational
from ..operators.locality import write_histogram
from ..operators.reorder import build_index, load_index, node_points, save_index
from ..operators.tiles import radius_summary, radius_tiles
from ..plans.ranks import global_rank
from ..session import scratch_dir
from ..sources import clouds, files
from . import sqltext as s

TABLE = re.compile(r"\{(\w+)\}")


def read(spark: SparkSession, d: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{table}.parquet")


def shared(text: str, spark: SparkSession, d: str) -> DataFrame:
    return spark.sql(text, **{t: read(spark, d, t) for t in set(TABLE.findall(text))})


#: name -> text that both engines run
SHARED = {
    "op_axis_projection": "SELECT o_orderkey AS pid, o_totalprice / cast(500 AS double) AS x, o_custkey + 0 AS y FROM {orders}",
    "op_attribute_carry": "SELECT o.o_orderkey AS pid, c.c_name AS owner FROM {orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey WHERE o.o_orderstatus = 'O'",
    "op_in_like_case": "SELECT p_partkey, CASE WHEN p_type LIKE '%BRASS' THEN 'brass' WHEN p_size BETWEEN 1 AND 10 THEN 'small' ELSE 'other' END AS class FROM {part} WHERE p_size IN (1, 2, 3, 5, 8, 13, 21, 34)",
    "op_null_handling": "SELECT count(*) AS n, count(o_totalprice) AS priced, cast(sum(CASE WHEN o_totalprice IS NULL OR isnan(o_totalprice) THEN 1 ELSE 0 END) AS bigint) AS bad FROM {orders}",
    "op_join_broadcast": "SELECT n.n_name, count(*) AS customers FROM {customer} c JOIN {nation} n ON c.c_nationkey = n.n_nationkey GROUP BY n.n_name",
    "op_join_left_outer": "SELECT c.c_custkey, count(o.o_orderkey) AS orders FROM {customer} c LEFT JOIN {orders} o ON o.o_custkey = c.c_custkey GROUP BY c.c_custkey",
    "op_join_full_outer": "SELECT coalesce(a.k, b.k) AS k, a.n AS orders, b.n AS events FROM (SELECT o_custkey AS k, count(*) AS n FROM {orders} GROUP BY 1) a FULL OUTER JOIN (SELECT user_id AS k, count(*) AS n FROM {events} GROUP BY 1) b ON a.k = b.k",
    "op_join_semi": "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 200000)",
    "op_join_anti": "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 200000)",
    "op_join_self": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "op_agg_hash": "SELECT o_orderstatus, count(*) AS n, min(o_orderkey) AS first, max(o_orderkey) AS last FROM {orders} GROUP BY o_orderstatus",
    "op_agg_distinct": "SELECT event_type, count(DISTINCT user_id) AS users FROM {events} GROUP BY event_type",
    "op_agg_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "op_agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)",
    "op_agg_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS n, cast(grouping(l_returnflag) AS int) AS g FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "op_agg_filtered": "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) AS n FROM {events} GROUP BY user_id",
    "op_agg_having": "SELECT user_id, count(*) AS n FROM {events} GROUP BY user_id HAVING count(*) > 5",
    "op_agg_arg_min": "SELECT o_custkey, min_by(o_orderkey, o_totalprice) AS cheapest FROM {orders} GROUP BY o_custkey",
    "op_agg_bool": "SELECT o_custkey, bool_or(o_totalprice > 100000) AS some, bool_and(o_totalprice > 1000) AS every_ FROM {orders} GROUP BY o_custkey",
    "op_agg_moments": "SELECT cast(sum(l_linenumber * l_linenumber) AS bigint) AS s2, cast(sum(l_linenumber) AS bigint) AS s1, count(*) AS n FROM {lineitem}",
    "op_window_ranking": "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS nt FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey)",
    "op_window_analytic": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY event_id)",
    "op_window_rows": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS earlier FROM {events}",
    "op_top_k": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "op_offset": "SELECT c_custkey FROM {customer} ORDER BY c_custkey LIMIT 5 OFFSET 20",
    "op_union_all": "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}",
    "op_intersect": "SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}",
    "op_except": "SELECT o_custkey AS k FROM {orders} EXCEPT SELECT user_id FROM {events}",
    "op_except_all": "SELECT c_nationkey AS k FROM {customer} EXCEPT ALL SELECT s_nationkey FROM {supplier}",
    "op_sample_hash": "SELECT o_orderkey FROM {orders} WHERE (o_orderkey * 2654435761) % 4294967296 < 42949673",
    "op_math_functions": "SELECT p_partkey, cast(floor(p_retailprice / 7) AS bigint) AS f, abs(p_size - 25) AS a, least(p_size, 10) AS lo, greatest(p_size, 40) AS hi FROM {part}",
    "op_string_functions": "SELECT p_partkey, length(p_name) AS n, upper(substring(p_name, 1, 5)) AS head, lpad(cast(p_size AS varchar(10)), 4, '0') AS padded, replace(p_type, ' ', '_') AS flat FROM {part}",
    "op_union_merge": "SELECT k, count(*) AS times FROM (SELECT DISTINCT o_custkey AS k FROM {orders} UNION ALL SELECT DISTINCT user_id AS k FROM {events}) x GROUP BY k",
}


def scan_pruned(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").filter("o_totalprice > 150000").select("o_orderkey")


def view(spark: SparkSession, d: str) -> DataFrame:
    read(spark, d, "part").createOrReplaceTempView("curvetree_part")
    t = spark.table("curvetree_part")
    return clouds.cloud_from(t, "p_partkey", ("p_partkey",), "0.5D * p_partkey", "20D * p_size", "10D * (p_retailprice - 900D)")


def through_file(fmt: str, spark: SparkSession, d: str) -> DataFrame:
    import uuid

    path = f"{scratch_dir(spark)}/xyz-{uuid.uuid4().hex}"
    cloud = clouds.load(spark, d, "part")
    if fmt in ("csv", "xyz"):
        cloud.write.csv(path, sep=" ")
        return files.read_xyz(spark, path).filter("_bad is null").drop("_bad") if fmt == "csv" else _source(spark, path)
    cloud.write.format(fmt).save(path)
    return files.read_any(spark, path, fmt)


def _source(spark: SparkSession, path: str) -> DataFrame:
    spark.dataSource.register(files.XyzSource)
    return spark.read.format("xyz").option("path", path.removeprefix("file:")).option("splitbytes", 4096).load()


def saved(spark: SparkSession, d: str) -> DataFrame:
    """A node's points, fetched from a saved index by its range."""
    import uuid

    path = f"{scratch_dir(spark)}/index-{uuid.uuid4().hex}"
    save_index(build_index(clouds.load(spark, d, "order"), "morton", 16, 2000), path)
    return node_points(load_index(spark, path).points, 100, 400).select("pid", "idx")


def kernel_predicate(spark: SparkSession, d: str) -> DataFrame:
    """One centre: the kernel's box goes to the scan, the distance is tested on what is left."""
    p, at = clouds.load(spark, d, "part"), (200.0, 500.0, 1000.0)
    for a, (lo, hi) in zip("xyz", SPHERE.bbox(at, 300.0), strict=False):
        p = p.filter(F.col(a).between(lo, hi))
    return p.filter(SPHERE.hits(tuple(map(F.col, "xyz")), tuple(map(F.lit, at)), F.lit(300.0))).select("pid")


def code_predicate(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    return encode(p, fit_grid(p), "morton").filter(F.col("code").between(3 << 57, (4 << 57) - 1)).select("pid", "code")


def filtered_search(before: bool, spark: SparkSession, d: str) -> DataFrame:
    """Nearest clicks: among clicks only, or clicks among the nearest of all."""
    p = clouds.load(spark, d, "event", attrs=True)
    q = clouds.id_centres(p.drop("event_type"))
    if before:
        clicks = p.filter("event_type = 'click'").drop("event_type")
        return relational.knn_relational(clicks, q, 5, fit_grid(clicks)).select("cid", "rank", "pid")
    near = relational.knn_relational(p.drop("event_type"), q, 5, fit_grid(p))
    return near.join(p.filter("event_type = 'click'").select("pid"), "pid", "left_semi").select("cid", "rank", "pid")


def shuffled_hash(spark: SparkSession, d: str) -> DataFrame:
    o, c = read(spark, d, "orders"), read(spark, d, "customer")
    return o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


def sort_merge(spark: SparkSession, d: str) -> DataFrame:
    o, li = read(spark, d, "orders"), read(spark, d, "lineitem")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


def lateral(spark: SparkSession, d: str) -> DataFrame:
    """Each customer's two dearest orders. Spark turns a lateral ORDER BY with LIMIT into row numbers in the order that rows
    happen to arrive in after a shuffle, so the rank is written out with its order."""
    ranked = "SELECT o_orderkey, o_custkey AS k, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM {orders}"
    return shared(f"SELECT c.c_custkey, t.o_orderkey FROM {{customer}} c, LATERAL (SELECT o_orderkey FROM ({ranked}) r WHERE r.k = c.c_custkey AND r.n <= 2) t", spark, d)


def cross_cloud(spark: SparkSession, d: str) -> DataFrame:
    """Orders near each of a few line items: two clouds, one distance predicate, joined by cells."""
    p, other = clouds.load(spark, d, "order"), clouds.load(spark, d, "part")
    q = clouds.id_centres(other)
    return relational.summarise(relational.radius_gridjoin(p, q, SPHERE, 150.0, fit_grid(p)), q)


def interval_join(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of events of different users less than a minute apart: a bucketed equi-join and a filter."""
    e = read(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    minute = 60_000_000
    a = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("t").alias("ta"), F.explode(F.array(*(F.expr(f"t div {minute} + {i}") for i in (-1, 0, 1)))).alias("m"))
    b = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("t").alias("tb"), F.expr(f"t div {minute}").alias("m"))
    return a.join(b, "m").filter((F.col("a") < F.col("b")) & (F.col("ua") != F.col("ub")) & (F.abs(F.col("ta") - F.col("tb")) < minute)).select("a", "b")


def as_of(spark: SparkSession, d: str) -> DataFrame:
    """For each order the last event of that user before it: one sorted pass over the union of both."""
    o = read(spark, d, "orders").select(F.col("o_custkey").alias("u"), F.col("o_orderdate").cast("timestamp_ntz").alias("t"), F.col("o_orderkey"), F.lit(None).cast("long").alias("e"))
    e = read(spark, d, "events").select(F.col("user_id").alias("u"), F.expr("ts - interval 25 years").alias("t"), F.lit(None).cast("long").alias("o_orderkey"), F.col("event_id").alias("e"))
    last = F.last("e", ignorenulls=True).over(Window.partitionBy("u").orderBy("t", F.col("e").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0))
    return o.union(e).withColumn("event_id", last).filter("o_orderkey is not null").select("o_orderkey", "event_id")


def approx_distinct(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").agg(F.approx_count_distinct("user_id").alias("users"))


def pivoted(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


def weighted_quantiles(spark: SparkSession, d: str) -> DataFrame:
    h = read(spark, d, "lineitem").groupBy("l_linenumber").count()
    return h.agg(F.expr("percentile(l_linenumber, array(0.25, 0.5, 0.75), count)").alias("q")).select(*(F.col("q")[i].alias(f"q{i + 1}") for i in range(3)))


def range_frame(spark: SparkSession, d: str) -> DataFrame:
    e = read(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(hour).alias("last_day"))


def sorts(spark: SparkSession, d: str) -> DataFrame:
    """A local sort, checked: how many rows follow a smaller one or none of their status, in the order that the partition
    really has. All rows do if it is sorted."""
    p = read(spark, d, "orders").select("o_orderstatus", "o_totalprice", "o_orderkey").repartition(4, "o_orderstatus").sortWithinPartitions("o_orderstatus", "o_totalprice", "o_orderkey")

    def follow(batches):
        last: dict = {}
        for b in batches:
            out = []
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                out.append(row[0] not in last or last[row[0]] <= row[1:])
                last[row[0]] = row[1:]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.bool_())], names=["o_orderstatus", "ok"])

    held = p.mapInArrow(follow, "o_orderstatus string, ok boolean")
    return held.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.col("ok").cast("long")).alias("in_order"))


def global_sort(spark: SparkSession, d: str) -> DataFrame:
    """A total order by range: each row's place, from ranks that no single task counts."""
    p = read(spark, d, "orders").select("o_orderkey", "o_totalprice")
    return global_rank(p, ["o_totalprice", "o_orderkey"], "place").select("o_orderkey", "place")


def window_edges(spark: SparkSession, d: str) -> DataFrame:
    spot = Window.partitionBy("user_id").orderBy("event_id")
    whole = spot.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(spark, d, "events").select("event_id", F.last_value("event_id").over(whole).alias("last"), F.round(F.percent_rank().over(spot), 9).alias("share"))


def json_structs(spark: SparkSession, d: str) -> DataFrame:
    """Fields parsed under a schema, and written back as text."""
    e = read(spark, d, "events").select("event_id", F.from_json("props", "k int").alias("p"))
    return e.select("event_id", F.col("p.k").alias("k"), F.to_json(F.struct(F.col("p.k").alias("k"))).alias("text"))


def bases(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "part").select("p_partkey", F.bin("p_partkey").alias("two"), F.lower(F.conv(F.col("p_partkey").cast("string"), 10, 16)).alias("sixteen"))


def knn_in_sql(spark: SparkSession, d: str) -> DataFrame:
    """The nearest five of each centre, by a table function joined laterally."""
    p = clouds.load(spark, d, "part")
    register_knn(spark, p, fit_grid(p))
    return spark.sql("SELECT q.cid, t.rank, t.pid FROM {q} q, LATERAL knn(q.cid, q.qx, q.qy, q.qz, 5) t", q=clouds.id_centres(p))


def histogram_sink(spark: SparkSession, d: str) -> DataFrame:
    """A cloud's histogram of cells written as delimited text with a header, and read back."""
    import uuid

    path = f"{scratch_dir(spark)}/histogram-{uuid.uuid4().hex}"
    p = clouds.load(spark, d, "order")
    coded = encode(p, fit_grid(p), "morton").groupBy(F.shiftright("code", 54).alias("d")).agg(F.count("*").alias("h"))
    write_histogram(coded.select(F.lit("morton").alias("curve"), "d", "h"), path)
    return spark.read.csv(path, schema="curve string, d long, h long", header=True)


def bits(spark: SparkSession, d: str) -> DataFrame:
    c = F.col("p_partkey")
    return read(spark, d, "part").select("p_partkey", F.shiftleft(c, 3).alias("l"), F.shiftright(c, 1).alias("r"), c.bitwiseAND(F.lit(5)).cast("long").alias("a"), c.bitwiseOR(F.lit(5)).cast("long").alias("o"), c.bitwiseXOR(F.lit(5)).cast("long").alias("x"), F.bit_count(c).cast("int").alias("n"))


def dates(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "orders").select("o_orderkey", F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01")).alias("days"), F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"))


def arrays(spark: SparkSession, d: str) -> DataFrame:
    e = read(spark, d, "embeddings")
    v = F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long"))
    return e.select("vec_id", F.size("embedding").alias("n"), F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.filter(v, lambda x: x > 0)).alias("positive"), F.element_at(v, 3).alias("third"))


def exploded(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "nation").select("n_nationkey", F.explode(F.sequence(F.lit(1), F.col("n_regionkey") + 1)).alias("i"))


def json_fields(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


def report_map(spark: SparkSession, d: str) -> DataFrame:
    counts = read(spark, d, "orders").groupBy("o_orderstatus").count()
    m = counts.agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "count"))).alias("m"))
    return m.select(F.col("m")["F"].alias("f"), F.col("m")["O"].alias("o"), F.size("m").alias("n"))


def sfc_in_sql(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    register(spark, fit_grid(p))
    return spark.sql("SELECT pid, sfc_code('hilbert', x, y, z) AS code FROM {p}", p=p)


def table_functions(spark: SparkSession, d: str) -> DataFrame:
    p = clouds.load(spark, d, "order")
    grid = fit_grid(p)
    register(spark, grid)
    x0, y0, z0 = grid.lo
    x1, y1, z1 = (a + e for a, e in zip(grid.lo, grid.ext, strict=True))
    return spark.sql(f"SELECT level, prefix, idx FROM octant_cover({x0}D, {x1}D, {y0}D, {y1}D, {z0}D, {z1}D, 1), range_points(2, 5)")


def union_of_ranges(spark: SparkSession, d: str) -> DataFrame:
    r = read(spark, d, "nation").select("n_regionkey", F.array(F.struct((F.col("n_nationkey") * 2).cast("long").alias("lo"), (F.col("n_nationkey") * 2 + 3).cast("long").alias("hi"))).alias("rs"))
    return r.groupBy("n_regionkey").agg(range_union("rs").alias("u")).select("n_regionkey", F.aggregate("u", F.lit(0).cast("long"), lambda a, s_: a + s_["hi"] - s_["lo"]).alias("covered"))


def cross_join(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "region").select("r_regionkey").crossJoin(F.broadcast(read(spark, d, "nation").select("n_nationkey")))


def range_join(spark: SparkSession, d: str) -> DataFrame:
    """Customers whose balance lies in one of a few ranges, found by hundreds and filtered."""
    c = read(spark, d, "customer").select("c_custkey", F.col("c_acctbal").alias("v"), F.floor(F.col("c_acctbal") / 100).alias("b"))
    r = spark.createDataFrame([(i, i * 700.0, i * 700.0 + 150.0) for i in range(10)], "rid long, lo double, hi double")
    cover = r.withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") / 100), F.floor(F.col("hi") / 100))))
    return c.join(F.broadcast(cover), "b").filter((F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi"))).select("rid", "c_custkey")


def whole_tiles(spark: SparkSession, d: str) -> DataFrame:
    """A kernel that holds the whole cloud answers from ranges alone."""
    p = clouds.load(spark, d, "order")
    index, q = build_index(p, "morton", 16, 2000), clouds.id_centres(p)
    return radius_summary(index, q, radius_tiles(index, q, KERNELS["cube"], 1e6))


_ORD = f"WITH p AS ({s.CLOUD['order']})"
_PART = f"SELECT * FROM ({s.CLOUD['part']}) x"
_EV = s.CLOUD["event"]
_CLICK = "e AS (SELECT event_id, event_type FROM events)"
OWN: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "op_scan_pruned": (scan_pruned, "SELECT o_orderkey FROM orders WHERE o_totalprice > 150000"),
    "op_catalog_view": (view, _PART),
    **{f"op_{f}_round_trip": (partial(through_file, f), _PART) for f in ("csv", "json", "orc", "xyz")},
    "op_saved_index": (saved, f"WITH {s.coded('order', 'morton')} SELECT pid, idx FROM k WHERE idx >= 100 AND idx < 400"),
    "op_kernel_predicate": (kernel_predicate, f"WITH p AS ({s.CLOUD['part']}), q AS (SELECT 200.0::DOUBLE AS qx, 500.0::DOUBLE AS qy, 1000.0::DOUBLE AS qz) SELECT pid FROM p, q WHERE {s.hit('sphere', 300.0)}"),
    "op_code_predicate": (code_predicate, f"WITH {s.coded('order', 'morton')} SELECT pid, code FROM k WHERE code BETWEEN {3 << 57} AND {(4 << 57) - 1}"),
    "op_filter_before_knn": (partial(filtered_search, True), f"WITH a AS ({_EV}), {s.by_id(100, 'a')}, {_CLICK}, p AS (SELECT a.* FROM a JOIN e ON e.event_id = a.pid WHERE event_type = 'click'), {s.knn(5)} SELECT cid, rank::INT AS rank, pid FROM n"),
    "op_filter_after_knn": (partial(filtered_search, False), f"WITH p AS ({_EV}), {s.by_id()}, {_CLICK}, {s.knn(5)} SELECT cid, rank::INT AS rank, pid FROM n JOIN e ON e.event_id = n.pid WHERE event_type = 'click'"),
    "op_join_shuffled_hash": (shuffled_hash, "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"),
    "op_join_sort_merge": (sort_merge, "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"),
    "op_join_cross": (cross_join, "SELECT r_regionkey, n_nationkey FROM region, nation"),
    "op_join_lateral": (lateral, "SELECT c.c_custkey, t.o_orderkey FROM customer c, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t"),
    "op_join_theta": (cross_cloud, f"WITH p AS ({s.CLOUD['order']}), o AS ({s.CLOUD['part']}), {s.by_id(100, 'o')} SELECT q.cid, count(p.pid) AS n, coalesce(sum(p.pid), 0)::BIGINT AS pid_sum FROM q LEFT JOIN p ON {s.hit('sphere', 150.0)} GROUP BY q.cid"),
    "op_join_range": (range_join, "SELECT rid, c_custkey FROM (SELECT i AS rid, i * 700.0::DOUBLE AS lo, i * 700.0::DOUBLE + 150 AS hi FROM range(10) t(i)) r JOIN customer ON c_acctbal >= lo AND c_acctbal < hi"),
    "op_join_interval": (interval_join, "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.event_id < b.event_id AND a.user_id <> b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) < 60000000"),
    "op_join_as_of": (as_of, "SELECT o_orderkey, e.event_id FROM orders o LEFT JOIN LATERAL (SELECT event_id FROM events WHERE user_id = o.o_custkey AND ts - INTERVAL 25 YEAR <= o.o_orderdate ORDER BY ts DESC, event_id DESC LIMIT 1) e ON true"),
    "op_agg_approx_distinct": (approx_distinct, None),
    "op_agg_pivot": (pivoted, "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1"),
    "op_agg_weighted_quantiles": (weighted_quantiles, "SELECT quantile_cont(l_linenumber, 0.25)::DOUBLE AS q1, quantile_cont(l_linenumber, 0.5)::DOUBLE AS q2, quantile_cont(l_linenumber, 0.75)::DOUBLE AS q3 FROM lineitem"),
    "op_window_range": (range_frame, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events"),
    "op_sort_local": (sorts, "SELECT o_orderstatus, count(*) AS n, count(*) AS in_order FROM orders GROUP BY 1"),
    "op_sort_global": (global_sort, "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS place FROM orders"),
    "op_window_edges": (window_edges, "SELECT event_id, last_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last, round(percent_rank() OVER (PARTITION BY user_id ORDER BY event_id), 9) AS share FROM events"),
    "op_json_structs": (json_structs, "SELECT event_id, json_extract_string(props, '$.k')::INT AS k, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS text FROM events"),
    "op_base_functions": (bases, "SELECT p_partkey, bin(p_partkey) AS two, lower(hex(p_partkey)) AS sixteen FROM part"),
    "op_udtf_knn": (knn_in_sql, f"WITH p AS ({s.CLOUD['part']}), {s.by_id()}, {s.knn(5)} SELECT cid, rank::INT AS rank, pid FROM n"),
    "op_histogram_sink": (histogram_sink, f"WITH {s.coded('order', 'morton')} SELECT 'morton' AS curve, code >> 54 AS d, count(*) AS h FROM k GROUP BY 2"),
    "op_bit_functions": (bits, "SELECT p_partkey, p_partkey << 3 AS l, p_partkey >> 1 AS r, p_partkey & 5 AS a, p_partkey | 5 AS o, xor(p_partkey, 5) AS x, bit_count(p_partkey)::INT AS n FROM part"),
    "op_date_functions": (dates, "SELECT o_orderkey, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m FROM orders"),
    "op_array_functions": (arrays, "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: round(x::DOUBLE * 1000)::BIGINT) AS v FROM embeddings) SELECT vec_id, len(v)::INT AS n, list_sum(v)::BIGINT AS total, len(list_filter(v, lambda x: x > 0))::INT AS positive, v[3] AS third FROM v"),
    "op_explode": (exploded, "SELECT n_nationkey, unnest(range(1, n_regionkey + 2))::INT AS i FROM nation"),
    "op_json_functions": (json_fields, "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events"),
    "op_map_functions": (report_map, "SELECT count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_orderstatus = 'O') AS o, count(DISTINCT o_orderstatus)::INT AS n FROM orders"),
    "op_udf_sql_code": (sfc_in_sql, f"WITH RECURSIVE {s.coded('order', 'hilbert')} SELECT pid, code FROM k"),
    "op_udtf": (table_functions, "SELECT 1::INT AS level, p AS prefix, i AS idx FROM range(8) a(p), range(2, 5) b(i)"),
    "op_udaf_range_union": (union_of_ranges, "WITH n AS (SELECT n_regionkey, unnest(range(n_nationkey * 2, n_nationkey * 2 + 3)) AS i FROM nation) SELECT n_regionkey, count(DISTINCT i) AS covered FROM n GROUP BY 1"),
    "op_whole_tiles": (whole_tiles, f"{_ORD}, {s.by_id()} SELECT cid, (SELECT count(*) FROM p) AS n, (SELECT sum(pid) FROM p)::BIGINT AS pid_sum FROM q"),
}
QUERIES = {**{n: partial(shared, t) for n, t in SHARED.items()}, **{n: f for n, (f, _) in OWN.items()}}
ORACLE = {**{n: TABLE.sub(r"\1", t) for n, t in SHARED.items()}, **{n: sql for n, (_, sql) in OWN.items() if sql}}
