"""Reordering a cloud along a curve, dense ranks, octant-aligned tiles, and the saved index."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import GridSpec, fit_grid
from ..plans.ranks import global_rank
from ..session import discard, materialise, small_frame
from .octree import build_counts

#: tiles are at least this large, and so much larger for larger clouds that about a million of them are enough
TILE_POINTS, MOST_TILES = 4_000_000, 4_000_000
#: points of one folder of the stored index, and the most folders
PART_POINTS, MOST_PARTS = 2_000_000, 4096


def reorder(cloud: DataFrame, curve: str, grid: GridSpec | None = None) -> DataFrame:
    """The cloud with code and ``idx``, its rank along the curve; equal codes by pid. Curve none: by pid."""
    grid = grid or fit_grid(cloud)
    return global_rank(encode(cloud, grid, curve), ["pid"] if curve == "none" else ["code", "pid"], "idx")


def rank_only(cloud: DataFrame, curve: str, grid: GridSpec) -> DataFrame:
    """pid, idx alone: coordinates are not carried through the sort."""
    coded = encode(cloud, grid, curve).select("pid", "code")
    ranked = global_rank(coded, ["pid"] if curve == "none" else ["code", "pid"], "idx")
    out = ranked.select("pid", "idx")
    out._scratch = ranked._scratch
    return out


@dataclass(frozen=True)
class Tiles:
    """Arrays over the tiles in the order of codes: octant, range of ranks along the curve, sum of ids."""

    level: np.ndarray
    prefix: np.ndarray
    idx_lo: np.ndarray
    idx_hi: np.ndarray
    pid_sum: np.ndarray

    def __len__(self) -> int:
        return len(self.level)


@dataclass(frozen=True)
class Index:
    """An ordered cloud in tiles. A tile is an octant that holds at most ``tile_points`` points, so it is one range of codes
    and one range of ranks; an octant of the last level with more is cut into several tiles by rank.

    With curve ``none`` points keep the order of acquisition: ``idx`` is that rank, and codes serve only to deal points
    into tiles, so a tile is no range of ``idx``."""

    points: DataFrame  # pid, x, y, z, code, idx, tile, part
    tiles: Tiles
    grid: GridSpec
    curve: str
    bucket: int  # N_max of the local octrees
    parts: int = 1  # folders that the points lie in

    @property
    def ordered(self) -> bool:
        return self.curve != "none"


def _cut(nodes: pd.DataFrame, tile_points: int, levels: int) -> Tiles:
    nodes = nodes.assign(first=nodes["prefix"].to_numpy(np.int64) << 3 * (levels - nodes["level"].to_numpy(np.int64))).sort_values("first")
    cnt = nodes["cnt"].to_numpy(np.int64)
    pieces = np.maximum(1, -(-cnt // tile_points))
    which = np.repeat(np.arange(len(cnt)), pieces)
    nth = np.arange(len(which)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    start = (np.cumsum(cnt) - cnt)[which]
    lo, hi = start + nth * tile_points, np.minimum(start + (nth + 1) * tile_points, start + cnt[which])
    return Tiles(nodes["level"].to_numpy(np.int64)[which], nodes["prefix"].to_numpy(np.int64)[which], lo, hi, np.zeros(len(which), np.int64))


def _tile_at(rank: F.Column, tiles: Tiles) -> F.Column:
    """The tile of each rank along the curve: binary search on Arrow batches."""
    first = tiles.idx_lo

    @F.pandas_udf("int")
    def find(ranks: pd.Series) -> pd.Series:
        return pd.Series((np.searchsorted(first, ranks.to_numpy(), side="right") - 1).astype(np.int32))

    return find(rank)


def part_of(tile: str, index_tiles: int, parts: int) -> F.Column:
    return F.expr(f"cast({tile} as long) * {parts} div {max(1, index_tiles)}").cast("int")


def build_index(cloud: DataFrame, curve: str = "hilbert", bucket: int = 128, tile_points: int | None = None, grid: GridSpec | None = None, total: int | None = None) -> Index:
    """Quantise, encode, sort once by range, cut the top tier from counts, store by tile.

    Ranks come from the sort, so no task sees all points of one code. The tiles are arrays on the driver, which searches
    broadcast: about 2 to 8 * N / tile_points of them, checked against a limit; by default ``tile_points`` grows with the
    cloud so that they stay well under it. Points lie in folders of successive tiles, so that a search reads only those it needs.
    ``total``: the number of points, where it is known.
    """
    grid = grid or fit_grid(cloud)
    coded = encode(cloud, grid, curve if curve != "none" else "morton").drop("cx", "cy", "cz")
    ranked = global_rank(coded, ["code", "pid"], "idx")
    stored = [ranked]
    total = ranked.count() if total is None else total
    tile_points = tile_points or max(TILE_POINTS, total // 250_000)
    nodes = build_counts(ranked.select("code"), tile_points, grid.levels)
    leaves = nodes.filter((F.col("cnt") <= tile_points) | (F.col("level") == grid.levels))
    tiles = _cut(small_frame(leaves.select("level", "prefix", "cnt"), MOST_TILES), tile_points, grid.levels)
    parts = max(1, min(MOST_PARTS, len(tiles), total // PART_POINTS))
    placed = ranked.withColumn("tile", _tile_at(F.col("idx"), tiles)).withColumn("part", part_of("tile", len(tiles), parts))
    if curve == "none":
        stored.append(global_rank(placed.drop("idx"), ["pid"], "idx"))
        placed = stored[-1].select(*ranked.columns, "tile", "part")
    points = materialise(placed, "points", by="part" if parts > 1 else None)
    for done in stored:
        discard(done)
    sums = small_frame(points.groupBy("tile").agg(F.sum("pid").alias("s")), MOST_TILES)
    tiles.pid_sum[sums["tile"].to_numpy(np.int64)] = sums["s"].to_numpy(np.int64)
    return Index(points, tiles, grid, curve, bucket, parts)


def save_index(index: Index, path: str, files: int | None = None) -> None:
    """Points sorted by idx in files of whole ranges, so that footers' ranges of idx, code and axes are tight; tiles as a table; the rest as one JSON row."""
    spark = index.points.sparkSession
    ordered = index.points.repartitionByRange(files, "idx") if files else index.points.repartitionByRange("idx")
    ordered.sortWithinPartitions("idx").write.mode("overwrite").parquet(f"{path}/points")
    names = ("level", "prefix", "idx_lo", "idx_hi", "pid_sum")
    table = pd.DataFrame({n: getattr(index.tiles, n) for n in names} | {"tile": np.arange(len(index.tiles))})
    spark.createDataFrame(table, ", ".join(f"{n} long" for n in table.columns)).write.mode("overwrite").parquet(f"{path}/tiles")
    facts = json.dumps({"grid": asdict(index.grid), "curve": index.curve, "bucket": index.bucket})
    spark.createDataFrame([(facts,)], "facts string").coalesce(1).write.mode("overwrite").parquet(f"{path}/facts")


def load_index(spark: SparkSession, path: str) -> Index:
    facts = json.loads(spark.read.parquet(f"{path}/facts").first()[0])
    t = small_frame(spark.read.parquet(f"{path}/tiles"), MOST_TILES).sort_values("tile")
    tiles = Tiles(*(t[n].to_numpy(np.int64) for n in ("level", "prefix", "idx_lo", "idx_hi", "pid_sum")))
    grid = facts["grid"]
    return Index(spark.read.parquet(f"{path}/points"), tiles, GridSpec(tuple(grid["lo"]), tuple(grid["ext"]), grid["levels"], grid["box"]), facts["curve"], facts["bucket"])


def node_points(points: DataFrame, lo: int, hi: int) -> DataFrame:
    """The points of any node: a range of idx that Parquet's row-group statistics narrow down."""
    return points.filter((F.col("idx") >= lo) & (F.col("idx") < hi))


def jump_profile(ordered: DataFrame, chunk: int = 1 << 20) -> DataFrame:
    """idx and the distance to the next point in order. Chunks of the order are separate windows; the first point of each
    chunk is also handed to the chunk before, so no jump is lost."""
    ends = ordered.filter(F.col("idx") % chunk == 0).filter("idx > 0").withColumn("__c", F.expr(f"idx div {chunk} - 1"))
    both = ordered.withColumn("__c", F.expr(f"idx div {chunk}")).unionByName(ends)
    spot = Window.partitionBy("__c").orderBy("idx")
    gaps = [F.lead(a).over(spot) - F.col(a) for a in "xyz"]
    jumps = both.select("idx", "__c", F.sqrt(gaps[0] * gaps[0] + gaps[1] * gaps[1] + gaps[2] * gaps[2]).alias("jump"))
    return jumps.filter(F.col("jump").isNotNull()).select("idx", "jump")
