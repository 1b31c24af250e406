"""Search kernels and predicates on boxes, as Spark columns and as NumPy functions that agree bit for bit.

Distances are squared sums taken left to right over x, y, z; membership is strict. Circle and square ignore z.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

EPS8 = 8 * 2.0**-52


@dataclass(frozen=True)
class Kernel:
    """dims: axes that count; round: Euclidean norm, else the largest difference. ``inside=False`` turns bulk acceptance off."""

    name: str
    dims: int
    round: bool
    inside: bool = True

    # -- Spark columns --------------------------------------------------------------------------------------------
    def hits(self, p: tuple[Column, ...], c: tuple[Column, ...], r: Column) -> Column:
        gaps = [a - b for a, b in zip(p[: self.dims], c[: self.dims], strict=True)]
        if self.round:
            return _sum([g * g for g in gaps]) < r * r
        return _all([F.abs(g) < r for g in gaps])

    def box_min_d2(self, lo: tuple[Column, ...], hi: tuple[Column, ...], c: tuple[Column, ...]) -> Column:
        return _sum([g * g for g in self._gaps(lo, hi, c)])

    def _gaps(self, lo, hi, c) -> list[Column]:
        return [F.greatest(lo[i] - c[i], c[i] - hi[i], F.lit(0.0)) for i in range(self.dims)]

    def box_disjoint(self, lo, hi, c, r: Column) -> Column:
        if self.round:
            return self.box_min_d2(lo, hi, c) >= r * r
        gaps = self._gaps(lo, hi, c)
        out = gaps[0] >= r
        for g in gaps[1:]:
            out = out | (g >= r)
        return out

    def box_inside(self, lo, hi, c, r: Column) -> Column:
        if not self.inside:
            return F.lit(False)
        far = [F.greatest(F.abs(c[i] - lo[i]), F.abs(hi[i] - c[i])) for i in range(self.dims)]
        return _sum([f * f for f in far]) < r * r if self.round else _all([f < r for f in far])

    def classify(self, lo, hi, c, r: Column) -> Column:
        return F.when(self.box_disjoint(lo, hi, c, r), "OUTSIDE").when(self.box_inside(lo, hi, c, r), "INSIDE").otherwise("PARTIAL")

    def bbox(self, c: tuple[Any, ...], r: Any) -> list[tuple[Any, Any]]:
        """The kernel's range on each axis that counts; others are unbounded."""
        return [(c[i] - r, c[i] + r) for i in range(self.dims)]

    # -- NumPy twins ----------------------------------------------------------------------------------------------
    def np_hits(self, p: np.ndarray, c: np.ndarray, r: np.ndarray) -> np.ndarray:
        if not self.round:
            return (np.abs(p[:, : self.dims] - c[:, : self.dims]) < np.asarray(r)[..., None]).all(axis=1)
        return np_d2(p, c, self.dims) < r * r

    def np_classify(self, lo: np.ndarray, hi: np.ndarray, c: np.ndarray, r: np.ndarray) -> np.ndarray:
        """-1 outside, 0 partial, 1 inside."""
        d = self.dims
        gap = np.maximum(np.maximum(lo[:, :d] - c[:, :d], c[:, :d] - hi[:, :d]), 0.0)
        far = np.maximum(np.abs(c[:, :d] - lo[:, :d]), np.abs(hi[:, :d] - c[:, :d]))
        if self.round:
            out, within = _np_squares(gap) >= r * r, _np_squares(far) < r * r
        else:
            out, within = (gap >= np.asarray(r)[..., None]).any(axis=1), (far < np.asarray(r)[..., None]).all(axis=1)
        if not self.inside:
            within = np.zeros_like(within)
        return np.where(out, -1, np.where(within, 1, 0))


SPHERE, CIRCLE = Kernel("sphere", 3, True), Kernel("circle", 2, True)
CUBE, SQUARE = Kernel("cube", 3, False), Kernel("square", 2, False)
KERNELS = {k.name: k for k in (SPHERE, CIRCLE, CUBE, SQUARE)}


def _sum(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out + p
    return out


def _all(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out & p
    return out


def _np_squares(g: np.ndarray) -> np.ndarray:
    out = g[:, 0] * g[:, 0]
    for i in range(1, g.shape[1]):
        out = out + g[:, i] * g[:, i]
    return out


def np_d2(p: np.ndarray, c: np.ndarray, dims: int = 3) -> np.ndarray:
    return _np_squares(p[:, :dims] - c[:, :dims])


def np_box_d2(lo: np.ndarray, hi: np.ndarray, c: np.ndarray) -> np.ndarray:
    return _np_squares(np.maximum(np.maximum(lo - c, c - hi), 0.0))


def d2(p: tuple[Column, ...], c: tuple[Column, ...]) -> Column:
    return _sum([(a - b) * (a - b) for a, b in zip(p, c, strict=True)])


def pad_box(lo, hi, ext):
    """Cell boxes, widened by a few ulps of their coordinates, since a boundary recomputed in reals may miss its own points."""
    big = np.maximum(np.maximum(np.abs(lo), np.abs(hi)), ext)
    return lo - EPS8 * big, hi + EPS8 * big
