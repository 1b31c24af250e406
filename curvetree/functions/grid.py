"""Quantisation of a cloud onto a grid of 2^L cells per axis."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import pad_box

LEVELS = 21


@dataclass(frozen=True)
class GridSpec:
    lo: tuple[float, float, float]
    ext: tuple[float, float, float]
    levels: int = LEVELS
    box: str = "axis"

    def np_cells(self, xyz: np.ndarray) -> np.ndarray:
        n, out = 1 << self.levels, np.zeros(xyz.shape, np.int64)
        for i in range(3):
            if self.ext[i] > 0:
                out[:, i] = np.clip(np.floor((xyz[:, i] - self.lo[i]) / self.ext[i] * float(n)), 0, n - 1)
        return out

    def np_boxes(self, level: np.ndarray, cells: np.ndarray, pad: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """Corners of the octants whose cell coordinates at their levels are given."""
        side = np.array(self.ext)[None, :] / (2.0 ** np.asarray(level, dtype=np.float64))[:, None]
        lo = np.array(self.lo)[None, :] + cells * side
        hi = lo + side
        return pad_box(lo, hi, np.array(self.ext)[None, :]) if pad else (lo, hi)


def fit_grid(cloud: DataFrame, levels: int = LEVELS, box: str = "axis") -> GridSpec:
    """The cloud's bounding box by one aggregation. ``cubic`` gives all axes the longest extent. An empty cloud gets a zero box."""
    if not 1 <= levels <= LEVELS or box not in ("axis", "cubic"):
        raise ValueError("1 to 21 levels; box axis or cubic")
    row = cloud.agg(*(f(a) for f in (F.min, F.max) for a in "xyz")).first()
    lo = tuple(float(v or 0.0) for v in row[:3])
    ext = tuple(float(b or 0.0) - a for a, b in zip(lo, row[3:], strict=True))
    return as_cubic(GridSpec(lo, ext, levels)) if box == "cubic" else GridSpec(lo, ext, levels)


def as_cubic(grid: GridSpec) -> GridSpec:
    return GridSpec(grid.lo, (max(grid.ext),) * 3, grid.levels, "cubic")


def cell(axis: Column, lo: float, ext: float, levels: int) -> Column:
    """Half-open cells; the upper corner is clamped into the last one, and so is what lies outside a frozen grid."""
    n = 1 << levels
    if ext <= 0:
        return F.lit(0)
    return F.greatest(F.lit(0), F.least(F.floor((axis - F.lit(lo)) / F.lit(ext) * F.lit(float(n))), F.lit(n - 1))).cast("int")


def quantise(df: DataFrame, grid: GridSpec) -> DataFrame:
    return df.withColumns({f"c{a}": cell(F.col(a), grid.lo[i], grid.ext[i], grid.levels) for i, a in enumerate("xyz")})
