"""Near duplicates among embeddings by products of int8 tiles with rigorous error bounds.

Each unit vector u becomes s * q + e: q of int8 components, s its own scale, |e| known exactly; the remainder e is
quantised once more in the same way. For two vectors the true cosine differs from s1 * s2 * (q1 . q2) by at most
|e1| + |e2| + |e1||e2|. A tile of products is computed on the first parts (exact in float32, whose sums stay under 2^24
for up to 1040 components, in float64 beyond); pairs that this bound leaves open are computed with both parts, whose
bound is about a hundredth of it; the few still open are joined to the vectors themselves and computed in double
precision. Every link with cosine >= threshold is found, none below it. Only the int8 parts travel between blocks.

Equal vectors are one row with a multiplicity, so groups of copies cost one row. Vectors are grouped into cells around
pivots; a cell is cut into blocks of bounded size, and only pairs of blocks are compared whose ranges of angles to
every pivot come within the threshold's angle (triangle inequality), which no link can escape. A task holds two
blocks. A pair of blocks sends on sums of links, one edge for each vector, and its open pairs.

Vectors that are null, zero, or hold null or non-finite components link with nothing, nor do vectors of different
lengths with one another. Components of any finite size count, the least and the largest doubles too. Vectors at
exactly the threshold link. Rows with a null id never link; rows that repeat an id with equal or other vectors are
rows of their own and give the same id twice. Very long vectors cost memory in proportion to a block. An empty table
gives no rows. Other columns are not read.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import connected_components, materialise, table

SLACK = 1e-9  # above all rounding of the bounds themselves


def units(x: np.ndarray) -> np.ndarray:
    """Each row divided by its norm. It is divided by its largest component first, which neither overflows nor underflows."""
    y = x / np.abs(x).max(axis=1, keepdims=True)
    return y / np.sqrt((y * y).sum(axis=1, keepdims=True))


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """q (int8), s, and what is left of each row."""
    scale = np.maximum(np.abs(x).max(axis=1), 1e-300) / 127
    q = np.rint(x / scale[:, None]).astype(np.int8)
    return q, scale, x - scale[:, None] * q


class Coded:
    """Rows of unit vectors as two int8 parts, with scales and the norms of what each part leaves."""

    def __init__(self, q1, s1, e1, q2, s2, e2):
        self.q1, self.s1, self.e1, self.q2, self.s2, self.e2 = q1, s1, e1, q2, s2, e2

    @classmethod
    def of(cls, unit: np.ndarray) -> Coded:
        q1, s1, rest = quantise(unit)
        q2, s2, last = quantise(rest)
        norm = lambda v: np.sqrt((v * v).sum(axis=1))
        return cls(q1, s1, norm(rest), q2, s2, norm(last))

    def take(self, at) -> Coded:
        return Coded(self.q1[at], self.s1[at], self.e1[at], self.q2[at], self.s2[at], self.e2[at])

    def __len__(self) -> int:
        return len(self.s1)


def tile_links(x: Coded, y: Coded | None, threshold: float, step: int = 1024) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, sure) of all pairs of rows of x and y that are links for sure, or may be; y None: within x, i < j."""
    same = y is None
    y = x if same else y
    kind = np.float32 if x.q1.shape[1] <= 1040 else np.float64
    py = y.q1.astype(kind).T
    out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool))]
    top = y.e1.max(initial=0.0)
    for a in range(0, len(x), step):
        part = x.take(slice(a, a + step))
        worst = part.e1.max()
        reach = (threshold - worst - top - worst * top - SLACK) / np.multiply.outer(part.s1, y.s1)
        i, j = np.nonzero(part.q1.astype(kind) @ py >= reach * (1 - 1e-6 * np.sign(reach)))
        i += a
        if same:
            i, j = i[i < j], j[i < j]
        for k in range(0, len(i), 1 << 18):
            out.append(_decide(x, y, i[k : k + (1 << 18)], j[k : k + (1 << 18)], threshold))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def _dot(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.einsum("ij,ij->i", a.astype(np.int32), b.astype(np.int32), dtype=np.int64).astype(np.float64)


def _decide(x: Coded, y: Coded, i: np.ndarray, j: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    first = x.s1[i] * y.s1[j] * _dot(x.q1[i], y.q1[j])
    bound = x.e1[i] + y.e1[j] + x.e1[i] * y.e1[j] + SLACK
    sure, some = first - bound >= threshold, np.flatnonzero(np.abs(first - threshold) < bound)
    keep = sure.copy()
    a, b = i[some], j[some]
    second = first[some] + x.s1[a] * y.s2[b] * _dot(x.q1[a], y.q2[b]) + x.s2[a] * y.s1[b] * _dot(x.q2[a], y.q1[b]) + x.s2[a] * y.s2[b] * _dot(x.q2[a], y.q2[b])
    bound = x.e2[a] + y.e2[b] + x.e2[a] * y.e2[b] + SLACK
    sure[some] = second - bound >= threshold
    keep[some] = second + bound >= threshold
    return i[keep], j[keep], sure[keep]


def _smallest_reachable(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Each node's smallest reachable node, by hooking and pointer jumping."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, root[i], low)
        np.minimum.at(new, root[j], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _matrix(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)


def _octets(column: pa.ChunkedArray) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.int8).reshape(len(column), -1)


def embedding_links(rows: DataFrame, threshold: float = 0.9, block_rows: int = 16_384, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """key, n_links, component_id, kept for each row."""
    v = F.col(vector)
    sound = F.col(key).isNotNull() & v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    plain = rows.select(F.col(key).alias("id"), F.coalesce(sound, F.lit(False)).alias("sound"), v.alias("x"))
    reps = plain.filter("sound").groupBy("x").agg(F.min("id").alias("node"), F.count("*").alias("times"))
    reps = materialise(reps, "vectors")
    widths = {r[0]: r[1] for r in reps.groupBy(F.size("x")).count().collect()}  # one row for each vector length in use
    angle = math.acos(max(-1.0, min(1.0, threshold))) + 1e-9
    linked = None
    for n, count in widths.items():
        part = _pairs_of_width(reps.filter(F.size("x") == n), count, threshold, angle, block_rows)
        linked = part if linked is None else linked.union(part)
    if linked is None:
        linked = rows.sparkSession.createDataFrame([], "node long, links long, other long")
    linked = materialise(linked, "links")
    comps = connected_components(linked.select(F.col("node").alias("src"), F.col("other").alias("dst")))
    sums = linked.groupBy("node").agg(F.sum("links").alias("links"))
    facts = reps.join(sums, "node", "left").join(comps, "node", "left").select("x", "times", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "node").alias("component"))
    good = plain.filter("sound").join(facts, "x", "left").select("id", (F.col("links") + F.col("times") - 1).alias("n_links"), F.col("component").alias("component_id"))
    lone = plain.filter("not sound").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return good.union(lone).select(F.col("id").alias(key), F.col("n_links").cast("long").alias("n_links"), "component_id", (F.col("id") == F.col("component_id")).alias("kept"))


def _pivots(reps: DataFrame, most: int) -> np.ndarray:
    """Up to ``most`` unit vectors far from one another, of a sample of 8 for each by hash (2,048 vectors at most)."""
    some = np.array([r[0] for r in reps.orderBy(F.xxhash64("x"), "node").limit(8 * most).select("x").collect()], np.float64)
    some, chosen = units(some), [0]
    near = some @ some[0]
    while len(chosen) < min(most, len(some)):
        chosen.append(int(near.argmin()))
        near = np.maximum(near, some @ some[chosen[-1]])
    return some[chosen]


def _pairs_of_width(reps: DataFrame, count: int, threshold: float, angle: float, block_rows: int) -> DataFrame:
    """(node, links, other) from all pairs of blocks of vectors of one length."""
    pivots = _pivots(reps, max(1, min(256, count // block_rows)))
    k = len(pivots)
    coded = "q1 binary, s1 double, e1 double, q2 binary, s2 double, e2 double"
    parts = [c.split()[0] for c in coded.split(", ")]

    def place(batches):
        for b in batches:
            if not b.num_rows:
                continue
            unit = units(_matrix(b.column("x")))
            c = Coded.of(unit)
            angles = np.arccos(np.clip(unit @ pivots.T, -1, 1))
            packed = [pa.array([r.tobytes() for r in v], pa.binary()) if v.ndim == 2 else pa.array(v) for v in (c.q1, c.s1, c.e1, c.q2, c.s2, c.e2)]
            yield pa.RecordBatch.from_arrays([b.column("node"), b.column("times"), *packed, pa.array(angles.argmin(axis=1).astype(np.int32)), pa.array([*angles], pa.list_(pa.float64()))], names=["node", "times", *parts, "cell", "angles"])

    placed = materialise(reps.select("x", "node", "times").mapInArrow(place, f"node long, times long, {coded}, cell int, angles array<double>"), "coded")
    ranges = placed.select("cell", *(F.col("angles")[i].alias(f"a{i}") for i in range(k))).groupBy("cell").agg(F.count("*").alias("n"), *(f(f"a{i}").alias(f"{n}{i}") for i in range(k) for n, f in (("lo", F.min), ("hi", F.max))))
    cells = {r["cell"]: (-(-r["n"] // block_rows), np.array([r[f"lo{i}"] for i in range(k)]), np.array([r[f"hi{i}"] for i in range(k)])) for r in ranges.collect()}  # at most 256 rows
    near = {c: [d for d in cells if ((cells[c][1] - cells[d][2] <= angle) & (cells[d][1] - cells[c][2] <= angle)).all()] for c in cells}
    starts, total = {}, 0
    for c, (blocks, _, _) in sorted(cells.items()):
        starts[c], total = total, total + blocks
    plan = [(c, starts[c], cells[c][0], [(starts[d], cells[d][0]) for d in near[c]]) for c in cells]  # at most 256 rows of 256 ranges
    route = reps.sparkSession.createDataFrame(plan, "cell int, start long, blocks long, near array<struct<first:bigint,n:bigint>>")
    dealt = placed.drop("angles").join(F.broadcast(route), "cell")
    dealt = dealt.withColumn("mine", F.col("start") + F.pmod(F.xxhash64("node"), F.col("blocks"))).withColumn("r", F.explode("near"))
    dealt = dealt.withColumn("o", F.explode(F.sequence("r.first", F.col("r.first") + F.col("r.n") - 1)))
    dealt = dealt.select("node", "times", *parts, "mine", (F.least("mine", "o") * F.lit(total) + F.greatest("mine", "o")).alias("pair"))

    def compare(group: pa.Table) -> pa.Table:
        c = Coded(*(_octets(group.column(p)) if p[0] == "q" else group.column(p).to_numpy() for p in parts))
        node, times, mine, pair = group.column("node").to_numpy(), group.column("times").to_numpy(), group.column("mine").to_numpy(), group.column("pair")[0].as_py()
        first, second = divmod(pair, total)
        a, b = np.flatnonzero(mine == first), np.flatnonzero(mine == second)
        i = j = np.zeros(0, np.int64)
        sure = np.zeros(0, bool)
        if first == second:
            i, j, sure = tile_links(c, None, threshold)
        elif len(a) and len(b):
            i, j, sure = tile_links(c.take(a), c.take(b), threshold)
            i, j = a[i], b[j]
        open_i, open_j, i, j = i[~sure], j[~sure], i[sure], j[sure]
        n = len(node)
        links = np.zeros(n, np.int64)
        np.add.at(links, i, times[j])
        np.add.at(links, j, times[i])
        order = np.argsort(node)
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        root = node[order][_smallest_reachable(n, rank[i], rank[j])[rank]]
        on = links > 0
        # an open pair has no number of links yet
        number = pa.array(np.concatenate((links[on], np.zeros(len(open_i), np.int64))), mask=np.concatenate((np.zeros(int(on.sum()), bool), np.ones(len(open_i), bool))))
        return pa.table({"node": np.concatenate((node[on], node[open_i])), "links": number, "other": np.concatenate((root[on], node[open_j]))})

    found = materialise(dealt.groupBy("pair").applyInArrow(compare, "node long, links long, other long"), "tile-links")
    vectors = reps.select("node", "times", "x")
    undecided = found.filter("links is null").select(F.col("node").alias("a"), F.col("other").alias("b"))
    both = undecided.join(vectors.select(F.col("node").alias("a"), F.col("times").alias("ta"), F.col("x").alias("xa")), "a").join(vectors.select(F.col("node").alias("b"), F.col("times").alias("tb"), F.col("x").alias("xb")), "b")

    def exactly(batches):
        for batch in batches:
            if batch.num_rows:
                cosine = (units(_matrix(batch.column("xa"))) * units(_matrix(batch.column("xb")))).sum(axis=1)
                yield batch.select(["a", "ta", "b", "tb"]).filter(pa.array(cosine >= threshold))

    links = both.select("a", "ta", "b", "tb", "xa", "xb").mapInArrow(exactly, "a long, ta long, b long, tb long")
    ends = links.select(F.explode(F.array(F.struct(F.col("a").alias("node"), F.col("tb").alias("links"), F.col("b").alias("other")), F.struct(F.col("b").alias("node"), F.col("ta").alias("links"), F.col("a").alias("other")))).alias("s")).select("s.*")
    return found.filter("links is not null").union(ends)


def op7_embedding_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All embeddings linked at cosine 0.9 or more."""
    return embedding_links(table(spark, sf_dir, "embeddings"))


ORACLE_OP7 = """WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
  u AS (SELECT vec_id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) AS e FROM v WHERE list_dot_product(e, e) > 0),
  l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a, u b WHERE a.vec_id <> b.vec_id AND list_dot_product(a.e, b.e) >= 0.9::DOUBLE),
  w AS (SELECT vec_id AS start, vec_id AS pos FROM v UNION SELECT w.start, l.b FROM w JOIN l ON l.a = w.pos),
  c AS (SELECT pos AS vec_id, min(start) AS component_id FROM w GROUP BY pos),
  n AS (SELECT a AS vec_id, count(*) AS n_links FROM l GROUP BY a)
SELECT c.vec_id, coalesce(n.n_links, 0) AS n_links, c.component_id, c.vec_id = c.component_id AS kept FROM c LEFT JOIN n ON n.vec_id = c.vec_id"""

QUERIES = {"op7_embedding_links": op7_embedding_links}
ORACLE = {"op7_embedding_links": ORACLE_OP7}
