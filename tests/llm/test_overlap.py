"""The near-duplicate stage against all pairs of shingle sets."""

from __future__ import annotations

import random
from itertools import combinations

import numpy as np

import corpus_pipeline
from curvetree.llm import overlap

from .test_other_operators import components, prose


def grams(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def similar(a, b):
    x, y = grams(a), grams(b)
    return len(x & y) >= 0.8 * len(x | y)


def near_copies(rng, n, lo, hi):
    """n pairs with similarities from lo to hi."""
    out = []
    while len(out) < n:
        a = prose(rng, rng.randint(60, 240)).split()
        b = [*a]
        for i in rng.sample(range(len(b)), rng.randint(1, len(b) // 30 + 2)):
            b[i] = "other"
        x, y = grams(" ".join(a)), grams(" ".join(b))
        if lo <= len(x & y) / len(x | y) < hi:
            out.append((" ".join(a), " ".join(b)))
    return out


def test_candidates_at_the_threshold():
    rng = random.Random(1)
    pairs = near_copies(rng, 300, 0.8, 0.85)
    met = [bool(np.any(np.equal(*(overlap.band_keys(overlap.shingle_set(t, 5), overlap.BANDS, overlap.ROWS) for t in p)))) for p in pairs]
    assert all(met)


def test_parities_never_differ_more_than_the_sets():
    rng = np.random.default_rng(3)
    for n in (0, 1, 5, 80, 700, 5000):
        every = rng.integers(0, 2**63, n + 60).astype(np.uint64)
        for gone in (0, 1, 7, 60):
            a, b = np.unique(every[gone:]), np.unique(every[: n + 60 - gone])
            bits = sum(int(x).bit_count() for x in (overlap.parities(a) ^ overlap.parities(b)).view(np.uint64))
            assert bits <= len(np.setxor1d(a, b))
            assert bits > 0 or not gone or not len(a)


def test_near_duplicate_stage_is_brute_force(spark, sf_dir):
    rng = random.Random(2)
    footer = "one line that is the same in all of them "
    texts = [t for p in near_copies(rng, 60, 0.8, 0.85) + near_copies(rng, 40, 0.7, 0.8) for t in p]
    texts += [footer * 60 + prose(rng, 40) for _ in range(6)] + ["a b c", "a b d", "a b c", "", None, " "]
    texts += [" ".join(w if rng.random() > 0.02 else "x" for w in texts[0].split()) for _ in range(30)]
    docs = dict(enumerate(texts))
    links = [(a, b) for a, b in combinations(docs, 2) if similar(docs[a], docs[b])]
    want = {a for a, c in components(docs, links).items() if a == c}
    table = spark.createDataFrame([*docs.items()], "doc_id long, text string").repartition(4)
    assert {r[0] for r in corpus_pipeline.drop_near_duplicates(spark, table, sf_dir).select("doc_id").collect()} == want
