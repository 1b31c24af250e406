"""From raw documents to packed training sequences: toxicity, near duplicates, repeated passages, packing.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept. All but the last return the
columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from curvetree.llm import overlap, packing, passages, simhash, toxicity
from curvetree.llm.common import materialise, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier scores 0.7 or more go."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.drop_toxic(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays. SimHash fingerprints of four-word shingles link at 4 or fewer differing bits; near
    copies that such short fingerprints miss are linked by sets of five-word shingles with a Jaccard similarity of 0.8 or
    more, verified. A group holds what either links."""
    by_fingerprint = materialise(simhash.near_duplicates(docs, shingle=4, max_distance=4), "simhash-groups")
    by_sets = materialise(overlap.near_duplicates(docs, shingle=5, similarity=0.8), "set-groups")
    return simhash.stay_one(docs, simhash.joined_groups(docs, [by_fingerprint, by_sets]), "doc_id", "text")


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 words or more stay in the document of the smallest id only."""
    return passages.drop_passages(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 4096 tokens."""
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_duplicates),
    ("substring_dedup", drop_repeated_passages),
    ("packing", pack),
]

#: The stages decide by fingerprints, chains and a trained classifier, which SQL can't express; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = materialise(docs, name)
    return docs
