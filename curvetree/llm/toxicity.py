"""Toxicity by a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

A document's features are the character n-grams of its distinct lower-cased words, with marks for word ends; the value
of a feature is the number of distinct words that hold it, scaled by the log ratio of its smoothed frequencies in
toxic and clean training documents. A logistic regression with an L2 penalty weighs the scaled features.

Training reads a bounded sample of labelled rows: at most ``sample`` of each label, those whose ids have the smallest
hashes. Scoring reads whole texts of all rows; since the score is a sum over distinct words, each word's part is
computed once and remembered. Labels, language, source and id are never inputs of a score. Null and empty texts get
the score of a document without words. Without labelled rows of both labels every score is the share of toxic labels
(0 if there are none).
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import map_columns, table

WORD = re.compile(r"[^\W\d_]+")
# fixed value: an odd multiplier that mixes 64-bit numbers
ROLL = np.uint64(0x9E3779B97F4A7C15)


def gram_slots(words: list[str], low: int, high: int, slots: int) -> tuple[np.ndarray, np.ndarray]:
    """(slot, word number) of all character n-grams of marked words, by rolling hashes over all words at once."""
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    points = np.frombuffer((" " + "  ".join(words) + " ").encode("utf-32-le"), "<u4").astype(np.uint64)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 2
    owner, left = np.repeat(np.arange(len(words)), sizes), np.repeat(np.cumsum(sizes), sizes) - np.arange(len(points))
    found, whose = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    h = np.zeros(len(points), np.uint64)
    for n in range(1, min(high, len(points)) + 1):
        h[: len(points) - n + 1] = h[: len(points) - n + 1] * ROLL + points[n - 1 :]
        if n >= low:
            ok = left >= n
            mixed = h[ok] ^ h[ok] >> np.uint64(29)
            found.append(((mixed * ROLL >> np.uint64(32)) % np.uint64(slots)).astype(np.int64))
            whose.append(owner[ok])
    return np.concatenate(found), np.concatenate(whose)


def distinct_words(text: str | None) -> set[str]:
    """The maximal runs of letters, lower-cased. Most parts between white space are one; only the others are searched."""
    if not text:
        return set()
    parts = set(text.lower().split())
    words = {p for p in parts if p.isalpha()}
    words.update(WORD.findall(" ".join(parts - words)))
    return words


@dataclass
class Classifier:
    """``weights``: the part of each hashed n-gram in ``places``, ratio and regression weight multiplied."""

    places: np.ndarray
    weights: np.ndarray
    bias: float
    low: int
    high: int
    slots: int
    room: int = 24_000_000
    parts: dict[str, float] = field(default_factory=dict)
    table: np.ndarray | None = None

    def __getstate__(self):
        return self.__dict__ | {"parts": {}, "table": None}

    def scores(self, texts: list[str | None], block_chars: int = 2_000_000) -> list[float]:
        """Between 0 and 1. Texts are taken in blocks of bounded size."""
        out: list[float] = []
        start = size = 0
        for i, t in enumerate(texts):
            size += len(t or "")
            if size >= block_chars or i + 1 == len(texts):
                out += self._block(texts[start : i + 1])
                start, size = i + 1, 0
        return out

    def _block(self, texts: list[str | None]) -> list[float]:
        """The parts of words not seen before are computed together."""
        if self.table is None:
            self.table = np.zeros(self.slots)
            self.table[self.places] = self.weights
        own, parts = [distinct_words(t) for t in texts], self.parts
        fresh = [*(set().union(*own) - parts.keys())]
        for k in range(0, len(fresh), 50_000):
            words = fresh[k : k + 50_000]
            slot, owner = gram_slots(words, self.low, self.high, self.slots)
            parts.update(zip(words, np.bincount(owner, self.table[slot], len(words)).tolist(), strict=True))
        out = []
        for words in own:
            margin = self.bias + math.fsum(map(parts.__getitem__, words))  # exact, whatever the order of a set
            out.append(1 / (1 + math.exp(-max(-50.0, min(50.0, margin)))))
        # words are remembered up to ``room`` bytes, each counted with its entry's overhead
        sizes = np.cumsum([len(w) + 120 for w in fresh])
        n = int(np.searchsorted(sizes, self.room, side="right"))
        self.room -= int(sizes[n - 1]) if n else 0
        for w in fresh[n:]:
            del parts[w]
        return out

    def score(self, text: str | None) -> float:
        return self.scores([text])[0]


def train(texts: list[str | None], toxic: list[int], low: int = 3, high: int = 6, least: int = 3, features: int = 20_000, penalty: float = 1e-3, rounds: int = 300, slots: int = 1 << 21) -> Classifier:
    """Fits on the given texts, in memory bounded by ``slots`` and the documents' selected n-grams.

    ``least``: documents that must hold an n-gram; ``features``: those of the largest evidence stay.
    """
    y = np.array(toxic, dtype=np.float64)
    share = float(y.mean()) if len(y) else 0.0
    if not 0 < share < 1:
        odds = math.log(share + 1e-9) - math.log(1 - share + 1e-9)
        return Classifier(np.zeros(0, np.int64), np.zeros(0), odds, low, high, slots)
    count = np.zeros((2, slots), np.int32)
    for t, label in zip(texts, toxic, strict=True):
        count[int(label)][np.unique(gram_slots([*distinct_words(t)], low, high, slots)[0])] += 1
    n_pos, n_neg = y.sum(), (1 - y).sum()
    both = count.sum(axis=0)
    strong = np.flatnonzero(both >= least)
    ratios = np.log((count[1][strong] + 1) / (n_pos + 2)) - np.log((count[0][strong] + 1) / (n_neg + 2))
    best = np.lexsort((strong, -np.abs(ratios) * np.sqrt(both[strong])))[:features]
    strong, ratios = strong[best], ratios[best]
    number = np.full(slots, -1, np.int32)
    number[strong] = np.arange(len(strong))
    rows, cols, times = [], [], []
    for i, t in enumerate(texts):
        own = number[gram_slots([*distinct_words(t)], low, high, slots)[0]]
        at, n = np.unique(own[own >= 0], return_counts=True)
        rows.append(np.full(len(at), i, np.int32))
        cols.append(at)
        times.append(n)
    row, col = np.concatenate(rows), np.concatenate(cols)
    value = np.concatenate(times) * ratios[col]
    weight = np.where(y > 0, 0.5 / n_pos, 0.5 / n_neg) * 0.5 + 0.5 / len(y)
    w, b = np.zeros(len(ratios)), 0.0
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for t in range(1, rounds + 1):
        margin = np.bincount(row, value * w[col], minlength=len(y)) + b
        gap = weight * (1 / (1 + np.exp(-np.clip(margin, -50, 50))) - y)
        gw = np.bincount(col, value * gap[row], minlength=len(w)) + penalty * w
        gb = gap.sum()
        m, v = 0.9 * m + 0.1 * gw, 0.999 * v + 0.001 * gw * gw
        mb, vb = 0.9 * mb + 0.1 * gb, 0.999 * vb + 0.001 * gb * gb
        rate = 0.03 * (1 - (t - 1) / rounds)
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        b -= rate * (mb / (1 - 0.9**t)) / (math.sqrt(vb / (1 - 0.999**t)) + 1e-8)
    return Classifier(strong, w * ratios, float(b), low, high, slots)


def held_out(key: F.Column) -> F.Column:
    """True where crc32(key as text) mod 3 is 1; never for a null key."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, sample: int = 2000, key: str = "doc_id", text: str = "text", label: str = "toxic", **options) -> Classifier:
    """A classifier from labelled rows outside the held-out third; at most ``sample`` of each label, so 2 * sample keys are
    broadcast and as many texts meet in one task, which trains. Only the weights come to the driver."""
    own = labels.select(F.col(key).alias("__k"), F.col(label).cast("int").alias("__y")).filter(F.col("__k").isNotNull() & F.col("__y").isin(0, 1) & ~held_out(F.col("__k")))
    own = own.withColumn("__h", F.xxhash64("__k"))
    chosen = [own.filter(F.col("__y") == y).orderBy("__h", "__k").limit(sample) for y in (1, 0)]
    picked = chosen[0].union(chosen[1]).dropDuplicates(["__k"])
    rows = docs.select(F.col(key).alias("__k"), F.col(text).alias("__t")).join(F.broadcast(picked), "__k").select("__k", "__t", "__y")

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, toxic = [], []
        for batch in batches:
            texts += batch.column(0).to_pylist()
            toxic += batch.column(1).to_pylist()
        if texts:
            m = train(texts, toxic, **options)
            yield pa.RecordBatch.from_arrays([pa.array([m.places.tolist()], pa.list_(pa.int64())), pa.array([m.weights.tolist()], pa.list_(pa.float64())), pa.array([m.bias])], names=["places", "weights", "bias"])

    one = rows.repartition(1).sortWithinPartitions("__k", F.col("__t").asc_nulls_first()).select("__t", "__y")
    made, empty = one.mapInArrow(learn, "places array<long>, weights array<double>, bias double").first(), train([], [], **options)
    if made is None:
        return empty
    return Classifier(np.array(made["places"], np.int64), np.array(made["weights"]), made["bias"], empty.low, empty.high, empty.slots)


def score_documents(docs: DataFrame, model: Classifier, threshold: float = 0.7, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, score, predicted for each row."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)  # at most ``features`` n-grams, whatever the corpus

    def run(ids, texts):
        scores = shared.value.scores(texts.to_pylist())
        return [ids, scores, np.array([s >= threshold for s in scores], np.int32)]

    kind = docs.schema[key].dataType.simpleString()
    return map_columns(docs, run, f"{key} {kind}, score double, predicted int", [key, text])


def drop_toxic(docs: DataFrame, model: Classifier, threshold: float = 0.7, text: str = "text") -> DataFrame:
    """The rows and columns of ``docs`` whose text scores below the threshold; nothing is shuffled."""
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = pa.array([s < threshold for s in shared.value.scores(batch.column(at).to_pylist())], pa.bool_())
            yield batch.filter(clean)

    return docs.mapInArrow(run, docs.schema)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A score for every document."""
    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"))
    return score_documents(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


QUERIES = {"op9_toxicity": op9_toxicity}
