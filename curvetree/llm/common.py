"""Helpers shared by the training-data operators: scratch tables, Arrow maps, connected components."""

from __future__ import annotations

import contextlib
import os
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import discard, materialise

__all__ = ["connected_components", "discard", "map_columns", "materialise", "portions", "release_shuffles", "single_thread", "table", "tokenizer_path", "utf8_length"]


def tokenizer_path(name: str) -> str:
    """Where a public vocabulary file lies; looked up on whichever machine asks."""
    import public_tokenizers

    return public_tokenizers.path(name)


def map_columns(df: DataFrame, fn: Callable[..., list], schema: str, columns: list[str]) -> DataFrame:
    """Arrow map: ``fn`` gets the named columns of a batch as Arrow arrays and returns the output columns."""
    names = [part.split()[0] for part in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x) for x in fn(*batch.columns)], names=names)
        give_back()

    return df.select(*columns).mapInArrow(run, schema)


def portions(batches: Iterator[pa.RecordBatch], rows: int = 1024) -> Iterator[pa.RecordBatch]:
    """Batches cut so that Python objects are made for a few rows at a time. At the end what the task has freed goes back to
    the system: workers live on after their task, and next to the other tasks' memory theirs counts in full."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)
    give_back()


def give_back() -> None:
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)


def release_shuffles(df: DataFrame) -> None:
    """Have Spark delete the shuffled files of queries that are over: it does so when the driver's JVM collects what referred to them."""
    df.sparkSession.sparkContext._jvm.System.gc()


def utf8_length(column: str) -> F.Column:
    return F.coalesce(F.octet_length(F.col(column)), F.lit(0)).cast("long")


def connected_components(edges: DataFrame, left: str = "src", right: str = "dst") -> DataFrame:
    """Components of an undirected graph as (node, component), component being the smallest node of each.

    Alternates two contractions, each one aggregation (combined before the shuffle) and one join that Spark may
    split: every node first hands its larger neighbours to the smallest one it sees, then its smaller ones. Ends
    when each component is a star around its smallest node, so links that are stars already take no round. Nodes
    without edges do not appear. Edges with a null end or equal ends are ignored.
    """
    a, b = F.col(left), F.col(right)
    pairs = edges.filter(a != b).select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).distinct()
    pairs = materialise(pairs, "edges")
    while True:
        ends = pairs.select(F.col("hi").alias("u"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(pairs.select("lo", F.lit(0), F.lit(1)))
        ends = ends.groupBy("u").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
        if not ends.filter("up + down > 1 and up > 0").count():
            break
        both = pairs.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(pairs.select("lo", "hi"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, "u").filter("v <> m").select(F.col("v").alias("hi"), F.col("m").alias("lo"))
        large = large.union(least.filter("u <> m").select("u", "m")).distinct()
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi").filter("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        last, pairs = pairs, materialise(small.union(low.select("hi", "m")).distinct(), "edges")
        discard(last)
    inner = pairs.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    return inner.union(pairs.select(F.col("lo"), F.col("lo")).distinct())


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def single_thread() -> None:
    """Keep native libraries from starting threads of their own inside a task."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
