"""Any table as a point cloud: expressions for the id, three axes and the order of acquisition."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.ranks import global_rank


@dataclass(frozen=True)
class CloudSpec:
    """Spark SQL expressions over ``table``. ``pid`` None: the rank by ``order``, which must then be a total order."""

    name: str
    table: str
    pid: str | None
    order: tuple[str, ...]
    x: str
    y: str
    z: str
    attrs: tuple[str, ...] = field(default=())


DAYS = "datediff(to_date({0}), date'1995-01-01')"
SPECS = {
    s.name: s
    for s in (
        CloudSpec("ship", "lineitem", None, ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_shipdate"), "20D * l_quantity", "l_extendedprice / 100D", f"0.4D * {DAYS.format('l_shipdate')}", ("l_returnflag",)),
        CloudSpec("order", "orders", "o_orderkey", ("o_orderkey",), "o_totalprice / 500D", f"0.4D * {DAYS.format('o_orderdate')}", "o_custkey * 1000D / {customers}D", ("o_orderstatus", "o_orderpriority")),
        CloudSpec("event", "events", "event_id", ("event_id",), "unix_micros(cast(ts as timestamp)) / 1D", "6D * user_id", "2D * value", ("event_type",)),
        CloudSpec("embed", "embeddings", "vec_id", ("vec_id",), "1000D * cast(embedding[0] as double)", "1000D * cast(embedding[1] as double)", "1000D * cast(embedding[2] as double)", ("label",)),
        CloudSpec("text", "documents", "doc_id", ("doc_id",), "n_chars / 10D", "cast(size(split(text, ' ', -1)) as double)", "10D * size(split(text, '\\n', -1))", ("lang",)),
        CloudSpec("part", "part", "p_partkey", ("p_partkey",), "0.5D * p_partkey", "20D * p_size", "10D * (p_retailprice - 900D)", ("p_type",)),
    )
}
EPOCH_2024 = 1704067200000000


def load(spark: SparkSession, sf_dir: str, name: str, attrs: bool = False) -> DataFrame:
    """pid, x, y, z (and the cloud's attributes) of a named cloud; only the columns its expressions use are read."""
    spec = SPECS[name]
    rows = spark.read.parquet(f"{sf_dir}/{spec.table}.parquet")
    z, x = spec.z, spec.x
    if "{customers}" in z:
        z = z.format(customers=spark.read.parquet(f"{sf_dir}/customer.parquet").count())
    if name == "event":
        x = f"(unix_micros(cast(ts as timestamp)) - {EPOCH_2024}L) / 2592000000D"
    return cloud_from(rows, spec.pid, spec.order, x, spec.y, z, spec.attrs if attrs else ())


def cloud_from(rows: DataFrame, pid: str | None, order: tuple[str, ...], x: str, y: str, z: str, attrs: tuple[str, ...] = ()) -> DataFrame:
    axes = {a: F.expr(e).cast("double") for a, e in (("x", x), ("y", y), ("z", z))}
    if pid is not None:
        return rows.select(F.expr(pid).cast("long").alias("pid"), *(c.alias(a) for a, c in axes.items()), *attrs)
    keyed = rows.select(*order, *(c.alias(a) for a, c in axes.items()), *(a for a in attrs if a not in order))
    return global_rank(keyed, list(order), "pid").select("pid", "x", "y", "z", *attrs)


def original_rank(cloud: DataFrame) -> DataFrame:
    """pid, idx: the order of acquisition, which the clouds' ids follow."""
    return global_rank(cloud.select("pid"), ["pid"], "idx")


def reject_invalid(cloud: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(valid, rejected): rows with a null, NaN or infinite coordinate go to the second."""
    bad = F.lit(False)
    for a in "xyz":
        bad = bad | F.col(a).isNull() | F.isnan(a) | (F.abs(F.col(a)) == float("inf"))
    return cloud.filter(~bad), cloud.filter(bad)


def all_centres(cloud: DataFrame) -> DataFrame:
    return cloud.select(F.col("pid").alias("cid"), *(F.col(a).alias(f"q{a}") for a in "xyz"))


def centre_hash(pid: str = "pid") -> F.Column:
    return (F.col(pid) * F.lit(2654435761)) % F.lit(4294967296)


def sample_centres(cloud: DataFrame, n: int) -> DataFrame:
    """The n ids of smallest hash: reproducible on any engine. A top-n, never a full sort."""
    return all_centres(cloud.orderBy(centre_hash(), "pid").limit(n))


def id_centres(cloud: DataFrame, step: int = 100) -> DataFrame:
    """All points whose id is divisible by ``step``: a set of centres that grows with the cloud."""
    return all_centres(cloud.filter(F.col("pid") % step == 0))


def share_of_centres(cloud: DataFrame, share: float) -> DataFrame:
    """Ids whose hash lies in the first ``share`` of its range."""
    return all_centres(cloud.filter(centre_hash() < F.lit(share * 2**32)))


def lattice_centres(spark: SparkSession, grid, inflate: float = 0.2) -> DataFrame:
    """27 points over the cloud's box inflated on each side, some outside it."""
    at = [[lo - inflate * e + i * (1 + 2 * inflate) * e / 2 for i in range(3)] for lo, e in zip(grid.lo, grid.ext, strict=True)]
    rows = [(i * 9 + j * 3 + k, at[0][i], at[1][j], at[2][k]) for i in range(3) for j in range(3) for k in range(3)]
    return spark.createDataFrame(rows, "cid long, qx double, qy double, qz double")
