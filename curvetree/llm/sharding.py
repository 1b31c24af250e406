"""Sharding by jump consistent hashing, in DataFrame expressions only.

A row's shard depends on its key and the number of shards alone. Adding a shard moves a row only into the new one.
No ring table exists. Null keys count as key 0. Repeated rows get the same shard and different slots.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, utf8_length

# fixed values: the multiplier of the hash's linear congruential generator, and an odd one for ordering buckets
STEP, SPREAD = 2862933555777941757, 2685821657736338717
LOW16, LOW32 = 0xFFFF, 0xFFFFFFFF


def _times(x: Column, factor: int) -> Column:
    """x * factor mod 2^64 on signed longs: 16-bit limbs, so that no product or sum overflows (ANSI mode raises)."""
    low, high = factor & LOW32, factor >> 32
    x_low, x_high = x.bitwiseAND(F.lit(LOW32)), F.shiftrightunsigned(x, 32)
    first = x_low.bitwiseAND(F.lit(LOW16)) * F.lit(low)
    second = F.shiftrightunsigned(first, 16) + F.shiftrightunsigned(x_low, 16) * F.lit(low)
    lower = F.shiftleft(second.bitwiseAND(F.lit(LOW16)), 16).bitwiseOR(first.bitwiseAND(F.lit(LOW16)))
    top = x_high.bitwiseAND(F.lit(LOW16)) * F.lit(low) + F.shiftleft((F.shiftrightunsigned(x_high, 16) * F.lit(low)).bitwiseAND(F.lit(LOW16)), 16)
    upper = (F.shiftrightunsigned(second, 16) + top + (x_low * F.lit(high)).bitwiseAND(F.lit(LOW32))).bitwiseAND(F.lit(LOW32))
    return F.shiftleft(upper, 32).bitwiseOR(lower)


def _next(key: Column) -> Column:
    product = _times(key, STEP)
    return F.when(product == F.lit(2**63 - 1), F.lit(-(2**63))).otherwise(product + F.lit(1))


def _jumps(key: Column, shards: int, rounds: int) -> Column:
    def jump(state: Column, _: Column) -> Column:
        key = _next(state["key"])
        to = F.floor((state["to"] + 1).cast("double") * (F.lit(2.0**31) / (F.shiftrightunsigned(key, 33) + 1).cast("double"))).cast("long")
        return F.when(state["to"] >= shards, state).otherwise(F.struct(key.alias("key"), state["to"].alias("at"), to.alias("to")))

    start = F.struct(key.alias("key"), F.lit(-1).cast("long").alias("at"), F.lit(0).cast("long").alias("to"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), start, jump)


def jump_shard(key: Column, shards: int) -> Column:
    """The shard of each key. The expected number of jumps is about ln(shards); rows that need over 64 get all they need."""
    if shards < 1:
        raise ValueError("at least one shard")
    key = F.coalesce(key.cast("long"), F.lit(0).cast("long"))
    quick = _jumps(key, shards, min(shards, 64))
    found = quick["at"] if shards <= 64 else F.when(quick["to"] >= shards, quick["at"]).otherwise(_jumps(key, shards, shards)["at"])
    return found.cast("int")


def assign_shards(rows: DataFrame, key: str, shards: int, buckets: int = 4096, grow: bool = True) -> DataFrame:
    """Adds ``shard``, ``slot`` (0, 1, ... without gaps in each shard) and ``grown_shard`` (with one shard more).

    Slots follow (bucket, key). The first pass reads the key column only and counts rows per shard and bucket: at most
    shards * buckets numbers, a bound that the data cannot move, so their running sums are broadcast. The second pass
    ranks inside each bucket. No task sees a whole shard. Buckets split a shard, not one key: rows that repeat a key
    stay together, as keys identify rows.
    """
    clean = F.coalesce(F.col(key).cast("long"), F.lit(0).cast("long"))
    bits = (buckets - 1).bit_length()
    bucket = (F.shiftrightunsigned(_times(clean, SPREAD), 64 - bits) if bits else F.lit(0)).cast("int")
    placed = {"shard": jump_shard(F.col(key), shards), "__bucket": F.pmod(bucket, F.lit(buckets))}
    counts = rows.select(key).withColumns(placed).groupBy("shard", "__bucket").count()
    starts = counts.selectExpr("shard", "__bucket", "sum(count) over (partition by shard order by __bucket rows between unbounded preceding and 1 preceding) as __start")
    plain = [f.name for f in rows.schema if f.name != key and "map<" not in f.dataType.simpleString() and f.dataType.simpleString() != "variant"]
    order = [F.col(key).asc_nulls_first(), *(F.col(f"`{c}`") for c in plain)]
    rank = F.row_number().over(Window.partitionBy("shard", "__bucket").orderBy(*order))
    ranked = rows.withColumns(placed).withColumn("__rank", rank)
    out = ranked.join(F.broadcast(starts), ["shard", "__bucket"]).withColumn("slot", F.coalesce("__start", F.lit(0)) + F.col("__rank").cast("long") - 1)
    grown = {"grown_shard": jump_shard(F.col(key), shards + 1)} if grow else {}
    return out.withColumns(grown).drop("__bucket", "__start", "__rank")


def op1_jump_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents into 8 shards by doc_id, with sizes, checksums and slots."""
    docs = table(spark, sf_dir, "documents").select(
        "doc_id", (utf8_length("text") + 1).alias("size"), F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32")
    )
    out = assign_shards(docs, "doc_id", 8)
    return out.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


#: DuckDB: CRC-32 of a hexadecimal string, given a table t of 256 entries, by folding over its bytes
CRC_TABLE = """SELECT list(v ORDER BY i) AS t FROM (SELECT i, list_reduce(list_prepend(i, range(8)),
  lambda a, s: CASE WHEN a & 1 = 1 THEN xor(a >> 1, 3988292384) ELSE a >> 1 END) AS v FROM (SELECT unnest(range(256))::BIGINT AS i))"""
CRC_OF_HEX = """4294967295 - list_reduce(list_prepend(4294967295::BIGINT, list_transform(range(1, length(h), 2), lambda p: ('0x' || substr(h, p, 2))::BIGINT)),
  lambda a, b: xor(a >> 8, t[(xor(a, b) & 255)::INT + 1]))"""


def _oracle() -> str:
    unsigned = "(CASE WHEN id < 0 THEN 18446744073709551616::HUGEINT + id ELSE id END)::UHUGEINT"
    full = "18446744073709551616::UHUGEINT"

    def steps(n: int) -> str:
        return f"""steps_{n} AS (SELECT id, {unsigned} AS k, 0::BIGINT AS j, -1::BIGINT AS b FROM ids UNION ALL
  SELECT id, nk, floor((j + 1)::DOUBLE * (2147483648.0::DOUBLE / ((nk >> 33)::DOUBLE + 1.0::DOUBLE)))::BIGINT, j
  FROM (SELECT *, (k * {STEP}::UHUGEINT + 1::UHUGEINT) % {full} AS nk FROM steps_{n} WHERE j < {n}) x)"""

    return f"""WITH RECURSIVE ids AS (SELECT DISTINCT coalesce(doc_id, 0) AS id FROM documents), {steps(8)}, {steps(9)},
tab AS ({CRC_TABLE}),
sums AS (SELECT text, {CRC_OF_HEX} AS crc FROM (SELECT text, hex(encode(text)) AS h FROM (SELECT DISTINCT coalesce(text, '') AS text FROM documents) x) y, tab),
placed AS (SELECT id, max(b)::INT AS shard, (({unsigned} * {SPREAD}::UHUGEINT) % {full}) >> 52 AS bucket FROM steps_8 GROUP BY id),
grown AS (SELECT id, max(b)::INT AS grown_shard FROM steps_9 GROUP BY id)
SELECT d.doc_id, (strlen(coalesce(d.text, '')) + 1)::BIGINT AS size, s.crc AS text_crc32, 'key' AS law, p.shard,
  row_number() OVER (PARTITION BY p.shard ORDER BY p.bucket, d.doc_id NULLS FIRST) - 1 AS slot, g.grown_shard
FROM documents d JOIN sums s ON coalesce(d.text, '') = s.text JOIN placed p ON p.id = coalesce(d.doc_id, 0) JOIN grown g ON g.id = p.id"""


QUERIES = {"op1_jump_shards": op1_jump_shards}
ORACLE = {"op1_jump_shards": _oracle()}
