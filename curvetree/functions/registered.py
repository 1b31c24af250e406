"""SQL-visible functions: a code function for a frozen grid, and table functions for ranges and octant covers."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..session import small_frame
from .curves import np_encode
from .grid import GridSpec


def register(spark: SparkSession, grid: GridSpec) -> None:
    """sfc_code(curve, x, y, z); range_points(lo, hi); octant_cover(x0, x1, y0, y1, z0, z1, level)."""

    @F.pandas_udf("long")
    def sfc_code(curve: pd.Series, x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
        cells, out = grid.np_cells(np.stack([x, y, z], axis=1)), np.zeros(len(x), np.int64)
        for c in curve.unique():
            at = (curve == c).to_numpy()
            out[at] = np_encode(cells[at], c, grid.levels)
        return pd.Series(out)

    class RangePoints:
        def eval(self, lo: int, hi: int) -> Iterator[tuple[int]]:
            return zip(range(lo, hi))

    class OctantCover:
        def eval(self, x0: float, x1: float, y0: float, y1: float, z0: float, z1: float, level: int) -> Iterator[tuple[int, int]]:
            n = 1 << level
            spans = []
            for i, (a, b) in enumerate(((x0, x1), (y0, y1), (z0, z1))):
                at = [0 if grid.ext[i] <= 0 else min(n - 1, max(0, int(np.floor((v - grid.lo[i]) / grid.ext[i] * n)))) for v in (a, b)]
                spans.append(range(at[0], at[1] + 1))
            for cx in spans[0]:
                for cy in spans[1]:
                    for cz in spans[2]:
                        yield level, int(np_encode(np.array([[cx, cy, cz]]), "morton", level))

    spark.udf.register("sfc_code", sfc_code)
    spark.udtf.register("range_points", F.udtf(RangePoints, returnType="idx: long"))
    spark.udtf.register("octant_cover", F.udtf(OctantCover, returnType="level: int, prefix: long"))


def register_knn(spark: SparkSession, cloud, grid: GridSpec, bucket: int = 32) -> None:
    """knn(cid, x, y, z, k) -> (rank, pid, d2) over a cloud of checked size, which goes to every task; for larger clouds
    there is ``knn_tiles``. Ties: the point of the centre's own id first, then by id."""
    from ..operators.local import LinearOctree

    rows = small_frame(cloud.select("pid", "x", "y", "z"))
    xyz = rows[["x", "y", "z"]].to_numpy(np.float64).reshape(-1, 3)
    codes = np_encode(grid.np_cells(xyz), "hilbert", grid.levels)
    order = np.lexsort((rows["pid"].to_numpy(), codes))
    shared = spark.sparkContext.broadcast((rows["pid"].to_numpy()[order], xyz[order], codes[order]))

    class Knn:
        def __init__(self):
            pid, points, own = shared.value
            self.pid, self.tree = pid, LinearOctree(points, own, grid, "hilbert", bucket)

        def eval(self, cid: int, x: float, y: float, z: float, k: int) -> Iterator[tuple[int, int, float]]:
            for i, (d2, _, pid) in enumerate(self.tree.knn(np.array([x, y, z]), k, self.pid, cid)):
                yield i + 1, pid, d2

    spark.udtf.register("knn", F.udtf(Knn, returnType="rank: int, pid: long, d2: double"))


def _union(ranges: pd.Series) -> Any:
    spans = sorted((s["lo"], s["hi"]) for rs in ranges for s in rs)
    out: list[list[int]] = []
    for lo, hi in spans:
        if out and lo <= out[-1][1]:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [{"lo": lo, "hi": hi} for lo, hi in out]


def range_union(ranges: Column | str) -> Column:
    """Aggregate: the union of rows' range lists, sorted, touching ones put together. A group's ranges meet in one task."""
    return F.pandas_udf("array<struct<lo:bigint,hi:bigint>>")(_union)(ranges)
