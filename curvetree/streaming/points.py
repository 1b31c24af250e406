"""Structured Streaming over point events: encoding, windowed octant counts, overfull octants, neighbour queries, proximity."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.curves import encode
from ..functions.grid import GridSpec
from ..functions.kernels import KERNELS
from ..operators.reorder import Index
from ..operators.tiles import merge_ranges, radius_tiles

__all__ = ["read_events", "encode_stream", "octant_windows", "session_counts", "overfull_octants", "neighbour_batches", "close_events"]


def read_events(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def encode_stream(points: DataFrame, grid: GridSpec, curve: str = "morton") -> DataFrame:
    """Codes under a frozen grid; points outside it fall into border cells and are flagged."""
    inside = F.lit(True)
    for i, a in enumerate("xyz"):
        inside = inside & F.col(a).between(grid.lo[i], grid.lo[i] + grid.ext[i])
    return encode(points.withColumn("outside", ~inside), grid, curve)


def octant_windows(coded: DataFrame, level: int, grid: GridSpec, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window start, prefix, n) for tumbling or sliding windows; rows later than the watermark are dropped."""
    prefix = F.shiftright("code", 3 * (grid.levels - level)).alias("prefix")
    frame = F.window("ts", length, slide) if slide else F.window("ts", length)
    counts = coded.withWatermark("ts", late).groupBy(frame.alias("w"), prefix).agg(F.count("*").alias("n"))
    return counts.select(F.col("w.start").alias("start"), "prefix", "n")


def session_counts(coded: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    counts = coded.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return counts.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


class _Overfull(StatefulProcessor):
    def __init__(self, bucket: int):
        self.bucket = bucket

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        before = self.count.get()[0] if self.count.exists() else 0
        now = before + sum(len(r) for r in rows)
        self.count.update((now,))
        if before <= self.bucket < now:
            yield pd.DataFrame({"prefix": [key[0]], "n": [now]})

    def close(self) -> None:
        pass


def overfull_octants(coded: DataFrame, level: int, grid: GridSpec, bucket: int) -> DataFrame:
    """Octants as they first pass ``bucket`` points: one counter for each octant in the state store."""
    keyed = coded.select(F.shiftright("code", 3 * (grid.levels - level)).alias("prefix"), "pid")
    return keyed.groupBy("prefix").transformWithStateInPandas(_Overfull(bucket), "prefix long, n long", "Update", "None")


def neighbour_batches(index: Index, r: float, sink: Callable[[DataFrame, int], None], kernel: str = "sphere") -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each batch of centres (cid, qx, qy, qz) is searched in the saved index."""

    def run(batch: DataFrame, number: int) -> None:
        sink(merge_ranges(radius_tiles(index, batch, KERNELS[kernel], r), batch), number)

    return run


def close_events(left: DataFrame, right: DataFrame, grid: GridSpec, level: int, within: str = "1 hour") -> DataFrame:
    """Pairs of two streams (id, ts, code) in one octant and within a time of each other; both need watermarks."""
    prefix = F.shiftright("code", 3 * (grid.levels - level))
    a = left.withWatermark("ts", "1 hour").select(F.col("id").alias("a"), F.col("ts").alias("ta"), prefix.alias("pa"))
    b = right.withWatermark("ts", "1 hour").select(F.col("id").alias("b"), F.col("ts").alias("tb"), prefix.alias("pb"))
    near = (F.col("tb") >= F.col("ta") - F.expr(f"interval {within}")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {within}"))
    return a.join(b, (F.col("pa") == F.col("pb")) & near).select("a", "b", "ta", "tb")
