"""Near duplicates by the overlap of shingle sets: candidates from bands of minima, every link verified on the sets.

A text's ``bands`` keys each mix ``rows`` minima of its shingle hashes under different permutations. Two sets of Jaccard
similarity s share a key with probability 1 - (1 - s^rows)^bands: for 40 bands of 6 rows all but 6 in a million at 0.8,
more above. A shared key only proposes a pair; it links if the sets themselves have ``similarity``.

Equal sets are made one first: the smallest id stands for all its rows. Each key's members are then compared with two
hubs, the smallest id and one picked by a hash of its own for each key, so that a group which shares many keys has many
hubs. That puts groups of copies together. Pairs of different groups whose minima differ too much for the similarity, by
four bits of each of them, are not proposed (``most_differing``), nor are those whose sets are shown to differ in too
many hashes by their ``parities``, a bound that loses nothing; only members that are in different groups after that are compared with
one another. Null and empty texts, and those of white space, have the empty set and are equal. Rows that repeat an id with
other texts are tied together. Rows with a null id are never linked.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, map_columns, materialise
from .simhash import shingle_hashes, stay_one

SIMILARITY, BANDS, ROWS = 0.8, 40, 6


def shingle_set(text: str | None, shingle: int) -> np.ndarray:
    """Sorted distinct hashes; empty for a text without words."""
    return np.unique(shingle_hashes(text, shingle))


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def band_keys(found: np.ndarray, bands: int, rows: int, seed: int = 42) -> np.ndarray:
    """One key a band."""
    least = minima(found, bands * rows, seed)
    return np.array([xxhash.xxh64_intdigest(least[i * rows : (i + 1) * rows].tobytes(), i) for i in range(bands)], np.uint64).view(np.int64)


def four_bits(least: np.ndarray) -> np.ndarray:
    """Four mixed bits of each minimum, 16 minima in a 64-bit number."""
    bits = ((least * np.uint32(0x9E3779B1)) >> np.uint32(28)).astype(np.uint8)
    bits = np.concatenate((bits, np.zeros(-len(bits) % 16, np.uint8)))
    return (bits[::2] | bits[1::2] << 4).view(np.int64)


def parities(found: np.ndarray) -> np.ndarray:
    """For each value of ten bits of a hash, whether an odd number of hashes has it: 1,024 bits in 64-bit numbers. Two sets'
    parities differ in at most as many bits as there are hashes in one set only."""
    odd = np.bincount((found & np.uint64(1023)).astype(np.int64), minlength=1024).astype(np.uint8) & 1
    return np.packbits(odd, bitorder="little").view(np.int64)


def most_differing(n: int, similarity: float) -> int:
    """Bits of ``four_bits`` of n minima that may differ at the similarity: the mean and six standard deviations more, so
    about one pair in 10^8 at the similarity itself has more, and fewer above it."""
    s = similarity
    spread = n * (s * 16 + (1 - s) * 5 - (4 * s + 2 * (1 - s)) ** 2)
    return int(np.ceil(n * 2 * (1 - s) + 6 * np.sqrt(max(spread, 0.0))))


def minima(found: np.ndarray, n: int, seed: int = 42) -> np.ndarray:
    """The least of the hashes under each of n permutations."""
    rng = np.random.default_rng(seed)
    flip, odd = (rng.integers(0, 2**32, n, np.uint32) for _ in range(2))
    low, high = found.astype(np.uint32), (found >> np.uint64(32)).astype(np.uint32)
    least = np.full(n, 2**32 - 1, np.uint32)
    for k in range(0, len(found), 1024):
        x = (low[k : k + 1024] ^ flip[:, None]) * (odd[:, None] | np.uint32(1))
        x ^= x >> np.uint32(15)
        x += high[k : k + 1024]
        x *= np.uint32(0x2C1B3C6D)
        least = np.minimum(least, x.min(axis=1))
    return least


def verified(docs: DataFrame, pairs: DataFrame, shingle: int, similarity: float, key: str, text: str) -> DataFrame:
    """Those (src, dst) whose texts' shingle sets have the similarity."""
    kind = docs.schema[key].dataType.simpleString()
    own = docs.filter(F.col(key).isNotNull()).select(F.col(key).alias("node"), F.col(text).alias("t"))
    there = own.join(pairs, F.col("node") == F.col("dst")).select("src", "dst", F.col("t").alias("b"))
    both = own.join(there, F.col("node") == F.col("src")).select("src", "dst", F.col("t").alias("a"), "b")

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, own_set = None, None
        for batch in batches:
            keep = []
            for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                if own_set is None or a != seen:
                    seen, own_set = a, shingle_set(a, shingle)
                keep.append(jaccard(own_set, shingle_set(b, shingle)) >= similarity)
            yield batch.filter(pa.array(keep, pa.bool_())).select([0, 1])

    return both.mapInArrow(judge, f"src {kind}, dst {kind}")


def near_duplicates(docs: DataFrame, shingle: int = 5, similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, component_id (the smallest key reachable by links) for each row."""
    kind = docs.schema[key].dataType.simpleString()

    def sketch(ids: pa.Array, texts: pa.Array) -> list:
        sets = [shingle_set(t, shingle) for t in texts.to_pylist()]
        least = [minima(s, bands * rows) if len(s) else None for s in sets]
        keys = [[xxhash.xxh64_intdigest(v[i * rows : (i + 1) * rows].tobytes(), i) for i in range(bands)] if v is not None else [] for v in least]
        keys = [np.array(k, np.uint64).view(np.int64) for k in keys]
        marks = [four_bits(v) if v is not None else np.zeros(0, np.int64) for v in least]
        odds = [parities(s) for s in sets]
        return [ids, pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()), pa.array(list(map(len, sets)), pa.int32()), pa.array(keys, pa.list_(pa.int64())), pa.array(marks, pa.list_(pa.int64())), pa.array(odds, pa.list_(pa.int64()))]

    own = materialise(map_columns(docs, sketch, f"{key} {kind}, same binary, size int, ks array<bigint>, marks array<bigint>, odds array<bigint>", [key, text]), "sketches")
    named = own.filter(F.col(key).isNotNull())
    reps = materialise(named.groupBy("same").agg(F.min(key).alias("node")), "representatives")
    # an id that repeats with other texts ties their sets together
    repeated = named.join(reps, "same").select(F.col(key).alias("src"), F.col("node").alias("dst")).filter("src <> dst")
    several = named.groupBy(key).agg(F.min("same").alias("lo"), F.max("same").alias("hi")).filter("lo <> hi").select(F.col(key).alias("src"))
    ties = repeated.join(several, "src", "left_semi")

    single = named.join(reps.withColumnRenamed("node", "rep"), "same").filter(F.col("rep") == F.col(key))
    sized = single.select(F.col("rep").alias("node"), "size", F.posexplode("ks").alias("band", "k"))
    heads = sized.groupBy("band", "k").agg(F.count("*").alias("n"), F.min(F.struct("node", "size")).alias("first"), F.min(F.struct(F.xxhash64("node", "band", "k"), "node", "size")).alias("other")).filter("n > 1")
    met = materialise(sized.join(heads, ["band", "k"]).select("band", "k", "node", "size", "first", F.struct("other.node", "other.size").alias("other")), "bands")
    fits = lambda a, b: F.least(a, b) >= F.lit(similarity) * F.greatest(a, b) - F.lit(1e-6)
    spokes = met.select("node", "size", F.explode(F.array("first", "other")).alias("h")).filter((F.col("node") != F.col("h.node")) & fits(F.col("size"), F.col("h.size")))
    spokes = spokes.select(F.least("node", "h.node").alias("dst"), F.greatest("node", "h.node").alias("src")).distinct()
    held = materialise(verified(docs, materialise(spokes, "spokes"), shingle, similarity, key, text).union(ties), "hub-links")
    dense = materialise(connected_components(held), "dense")

    placed = met.join(dense, "node", "left").select("band", "k", "node", "size", F.coalesce("component", "node").alias("group"))
    mixed = placed.groupBy("band", "k").agg(F.min("group").alias("lo"), F.max("group").alias("hi")).filter("lo <> hi").select("band", "k")
    signs = single.select(F.col("rep").alias("node"), "marks", "odds").distinct()
    placed = materialise(placed.join(mixed, ["band", "k"], "left_semi").join(signs, "node"), "mixed")
    a, b = placed.alias("a"), placed.alias("b")
    apart = (F.col("a.band") == F.col("b.band")) & (F.col("a.k") == F.col("b.k")) & (F.col("a.group") != F.col("b.group")) & (F.col("a.node") > F.col("b.node")) & fits(F.col("a.size"), F.col("b.size"))
    differing = lambda signs, n: sum((F.bit_count(F.col(f"a.{signs}")[i].bitwiseXOR(F.col(f"b.{signs}")[i])) for i in range(n)), F.lit(0))
    alone = F.lit((1 - similarity) / (1 + similarity)) * (F.col("a.size") + F.col("b.size")) + F.lit(1e-6)  # hashes in one set only
    apart = apart & (differing("odds", 16) <= alone) & (differing("marks", -(-bands * rows // 16)) <= most_differing(bands * rows, similarity))
    rest = a.join(b, apart).select(F.col("a.node").alias("src"), F.col("b.node").alias("dst")).distinct().join(spokes, ["src", "dst"], "left_anti")
    across = verified(docs, materialise(rest, "pairs"), shingle, similarity, key, text)
    # groups, not their members, are put together by the links found across them
    of = lambda end: dense.select(F.col("node").alias(end), F.col("component").alias(f"{end}_group"))
    bridges = across.join(of("src"), "src", "left").join(of("dst"), "dst", "left")
    comps = connected_components(bridges.select(F.coalesce("src_group", "src").alias("src"), F.coalesce("dst_group", "dst").alias("dst")))
    groups = reps.join(dense, "node", "left").select("same", F.coalesce("component", "node").alias("group"))
    groups = groups.join(comps, F.col("group") == F.col("node"), "left").select("same", F.coalesce("component", "group").alias("component_id"))
    return own.join(groups, "same", "left").select(key, F.when(F.col(key).isNotNull(), F.col("component_id")).alias("component_id"))


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """The rows and columns of ``docs`` less near duplicates: of each group the row of the smallest key stays."""
    return stay_one(docs, near_duplicates(docs, key=key, text=text, **options), key, text)
