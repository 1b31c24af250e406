"""Near duplicates by SimHash fingerprints and multi-index hashing.

A fingerprint is cut into segments. Two fingerprints within ``max_distance`` bits agree in at least one segment up to a
few bits, so each probes that segment's table with every value of a small Hamming ball. A ball of radius 2 is met half
way: both sides list radius 1, which takes fewer keys than one side's radius 2. Complete distances are verified
inside the join, so only true links leave it.

Fingerprints are made equal first: one representative (the smallest id) stands for all rows of a fingerprint, so a
group of copies costs one row. A dense group of near copies is put together next, by links to a few hubs of each table
entry; the search then lists links between such groups only, so it never lists all pairs within one. Null and empty texts, and those of white space, have the fingerprint zero and link like
any other. Rows with a null id get a fingerprint and a null component. Texts are read whole.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import connected_components, map_columns, materialise, table

LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
BITS = 64


def shingle_hashes(text: str | None, shingle: int, seed: int = 42) -> np.ndarray:
    """Of each run of ``shingle`` words, repeats included; of the whole text if it is shorter."""
    words = (text or "").encode().translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate((np.zeros(1, np.int64), ends[:-1]))
    n, digest = max(1, len(words) - shingle + 1), xxhash.xxh64_intdigest
    last = ends[shingle - 1 :] if len(words) >= shingle else ends[-1:]
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts[:n].tolist(), (last - 1).tolist(), strict=True)], "<u8")


def fingerprint(text: str | None, shingle: int, seed: int = 42) -> int:
    """As a signed 64-bit number. A bit is set if it is set in over half the shingles' hashes, repeats included."""
    hashes = shingle_hashes(text, shingle, seed)
    n, counts = len(hashes), np.zeros(BITS, np.int64)
    for k in range(0, n, 8192):
        counts += np.unpackbits(hashes[k : k + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, shingle: int, seed: int = 42, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and ``fp`` for each row."""
    kind = docs.schema[key].dataType.simpleString()
    return map_columns(docs, lambda ids, texts: [ids, np.array([fingerprint(t, shingle, seed) for t in texts.to_pylist()], np.int64)], f"{key} {kind}, fp long", [key, text])


def segments(count: int) -> list[tuple[int, int]]:
    """(shift, width) of each segment."""
    cuts = [BITS * i // count for i in range(count + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def _ball(fp: Column, number: int, shift: int, width: int, radius: int) -> list[Column]:
    value = F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << width) - 1))
    masks = [0]
    for _ in range(radius):
        masks = sorted({m ^ (1 << b) for m in masks for b in range(width)} | {*masks})
    # the number of the segment stands above the value; widths stay under 58
    return [value.bitwiseXOR(F.lit(m)).bitwiseOR(F.lit(number << 58)) for m in masks]


def radii(max_distance: int, count: int) -> list[int]:
    """The radius that each segment must be searched with; -1: not at all. The first few carry the remainder."""
    least, extra = divmod(max_distance, count)
    return [least if i <= extra else least - 1 for i in range(count)]


def hub_links(reps: DataFrame, max_distance: int, segment_count: int, hubs: int = 4, node: str = "node", fp: str = "fp") -> DataFrame:
    """(src, dst), some of the links: those between a fingerprint and the hubs of each of its segments' values. Hubs are
    picked by hash, so there are at most ``hubs`` rows for each fingerprint and segment, however many share a value."""
    keys = [key for i, (shift, width) in enumerate(segments(segment_count)) for key in _ball(F.col(fp), i, shift, width, 0)]
    own = reps.select(F.col(node).alias("src"), F.col(fp).alias("fa"), F.explode(F.array(*keys)).alias("k"))
    picked = [F.min(F.struct(F.xxhash64("src", F.lit(i)).alias("by"), F.col("src").alias("dst"), F.col("fa").alias("fb"))) for i in range(hubs)]
    heads = own.groupBy("k").agg(F.array_distinct(F.array(*(p.dropFields("by") for p in picked))).alias("heads"), F.count("*").alias("n")).filter("n > 1")
    near = own.join(heads.select("k", F.explode("heads").alias("h")), "k")
    return near.filter((F.col("src") != F.col("h.dst")) & (F.bit_count(F.col("fa").bitwiseXOR(F.col("h.fb"))) <= max_distance)).select("src", F.col("h.dst").alias("dst"))


def links(reps: DataFrame, max_distance: int, segment_count: int, node: str = "node", fp: str = "fp", group: str | None = None) -> DataFrame:
    """(src, dst) for all pairs of distinct fingerprints within max_distance. A pair may appear more than once.

    With ``group`` src and dst are the groups of all such pairs that lie in two groups. Keys at which fewer than two
    groups meet go first, so a dense group that shares a key is not compared within itself."""
    if BITS // segment_count > 57 or segment_count < 2:
        raise ValueError("at least two segments")
    probe, stored, once = [], [], F.lit(False)
    for i, ((shift, width), r) in enumerate(zip(segments(segment_count), radii(max_distance, segment_count), strict=True)):
        if r >= 0:
            probe += _ball(F.col(fp), i, shift, width, r - r // 2)
            stored += _ball(F.col(fp), i, shift, width, r // 2)
            part = lambda c, shift=shift, width=width: F.shiftrightunsigned(c, shift).bitwiseAND(F.lit((1 << width) - 1))
            apart = part(F.col("fa").bitwiseXOR(F.col("fb")))
            # two balls share many values; of those that meet half way only the one is taken that the lowest differing bit leads to
            first = F.when(F.bit_count(apart) > r // 2, apart.bitwiseAND(-apart)).otherwise(F.lit(0)) if r == 2 else None
            here = F.shiftrightunsigned(a_k := F.col("k"), 58) == i
            once = once | (here if first is None else here & (a_k.bitwiseAND(F.lit((1 << width) - 1)).bitwiseXOR(part(F.col("fa"))) == first))
    end = group or node  # each pair meets both ways round, so < leaves it once
    a = reps.select(F.col(end).alias("src"), F.col(fp).alias("fa"), F.explode(F.array(*probe)).alias("k"))
    b = reps.select(F.col(end).alias("dst"), F.col(fp).alias("fb"), F.explode(F.array(*stored)).alias("k"))
    near = F.bit_count(F.col("fa").bitwiseXOR(F.col("fb"))) <= max_distance
    seen = a.select("k", F.col("src").alias("g"), F.lit(1).alias("side")).union(b.select("k", F.col("dst").alias("g"), F.lit(2).alias("side")))
    meet = seen.groupBy("k").agg(F.min("g").alias("lo"), F.max("g").alias("hi"), F.bit_or("side").alias("sides")).filter("lo <> hi and sides = 3").select("k")
    meet = materialise(meet, "meeting-keys")
    a, b = a.join(meet, "k", "left_semi"), b.join(meet, "k", "left_semi")
    b = b.withColumnRenamed("k", "__k")
    return a.join(b, (F.col("k") == F.col("__k")) & (F.col("src") < F.col("dst")) & near & once).select("src", "dst")


def near_duplicates(docs: DataFrame, shingle: int = 4, max_distance: int = 4, segment_count: int = 3, link_segments: int = 2, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, fp, component_id (the smallest key reachable by links) for each row.

    Hubs are those of ``segment_count`` segments; the search for all links cuts in ``link_segments``. Two halves of 32 bits
    each take some hundred keys for a fingerprint, but unlike texts meet at one of them 40 times more seldom than at
    one of three thirds, which grows with the square of the table."""
    own = materialise(fingerprints(docs, shingle, key=key, text=text), "fingerprints")
    reps = materialise(own.filter(F.col(key).isNotNull()).groupBy("fp").agg(F.min(key).alias("node")), "representatives")
    # an id that repeats with other texts ties their fingerprints together
    repeated = own.filter(F.col(key).isNotNull()).join(reps, "fp").select(F.col(key).alias("src"), F.col("node").alias("dst")).filter("src <> dst")
    several = own.groupBy(key).agg(F.min("fp").alias("lo"), F.max("fp").alias("hi")).filter("lo <> hi").select(F.col(key).alias("src"))
    ties = repeated.join(several, "src", "left_semi")
    dense = connected_components(hub_links(reps, max_distance, segment_count).union(ties))
    grouped = materialise(reps.join(dense, "node", "left").select("fp", F.coalesce("component", "node").alias("group")), "groups")
    comps = connected_components(links(grouped, max_distance, link_segments, group="group"))
    named = grouped.join(comps, F.col("group") == F.col("node"), "left").select("fp", F.coalesce("component", "group").alias("component_id"))
    return own.join(named, "fp", "left").select(key, "fp", F.when(F.col(key).isNotNull(), F.col("component_id")).alias("component_id"))


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The rows and columns of ``docs`` less near duplicates: of each group the row of the smallest key stays, one row if
    that key repeats. Rows with a null key stay."""
    return stay_one(docs, near_duplicates(docs, key=key, text=text, **options), key, text)


def joined_groups(docs: DataFrame, groupings: list[DataFrame], key: str = "doc_id") -> DataFrame:
    """key, component_id: what any of the groupings (key, component_id) puts together, also by way of another, is one group."""
    edges = None
    for g in groupings:
        part = g.filter(F.col(key) != F.col("component_id")).select(F.col(key).alias("src"), F.col("component_id").alias("dst"))
        edges = part if edges is None else edges.union(part)
    comps = connected_components(edges)
    return docs.select(key).join(comps, F.col(key) == F.col("node"), "left").select(key, F.coalesce("component", key).alias("component_id"))


def stay_one(docs: DataFrame, groups: DataFrame, key: str, text: str) -> DataFrame:
    """Of each group (key, component_id) the row whose key names it; rows with a null key too."""
    stay = groups.filter(F.col(key) == F.col("component_id")).select(F.col(key).alias("__stay")).distinct()
    kept = docs.join(stay, docs[key] == F.col("__stay"), "left_semi")
    first = Window.partitionBy(key).orderBy(F.col(text).asc_nulls_first())
    kept = kept.withColumn("__nth", F.row_number().over(first)).filter("__nth = 1").drop("__nth")
    return kept.union(docs.filter(F.col(key).isNull()))


def op3_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents: fingerprints of four-word shingles, linked at 4 or fewer differing bits."""
    out = near_duplicates(table(spark, sf_dir, "documents"), shingle=4, max_distance=4)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {"op3_simhash_groups": op3_simhash_groups}
