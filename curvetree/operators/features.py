"""What neighbourhoods are for: density, local shape, components."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernels import SPHERE, Kernel
from ..sources.clouds import all_centres
from ..session import materialise
from .local import spread
from .relational import radius_gridjoin


def density(cloud: DataFrame, grid, kernel: Kernel, r: float) -> DataFrame:
    """(cid, n, density): neighbours for each unit of volume (area for flat kernels)."""
    volume = {"sphere": 4 / 3 * np.pi * r**3, "circle": np.pi * r * r, "cube": 8 * r**3, "square": 4 * r * r}[kernel.name]
    return count_neighbours(cloud, grid, kernel, r).select("cid", "n", (F.col("n") / F.lit(float(volume))).alias("density"))


def count_neighbours(cloud: DataFrame, grid, kernel: Kernel, r: float) -> DataFrame:
    """(cid, n) of every point: exact counts, no pair is made a row.

    Points go to blocks of four radii and, within a radius of its border, to the neighbouring block too."""
    axes, side = "xyz"[: kernel.dims], 4.0 * r
    reach = F.lit(r * (1 + 1e-9) + max(grid.ext) * 1e-12)
    sound = F.lit(True)
    for a in "xyz":
        sound = sound & F.col(a).isNotNull() & ~F.isnan(a) & (F.abs(a) != float("inf"))
    placed, home = cloud.filter(sound).select("pid", "x", "y", "z"), F.lit(True)
    for a in "xyz":
        if a in axes:
            at = lambda v, a=a: F.floor((v - F.lit(grid.lo["xyz".index(a)])) / F.lit(side))
            placed = placed.withColumn(f"b{a}", F.explode(F.sequence(at(F.col(a) - reach), at(F.col(a) + reach))))
            home = home & (F.col(f"b{a}") == at(F.col(a)))
        else:
            placed = placed.withColumn(f"b{a}", F.lit(0).cast("long"))
    placed = placed.withColumn("home", home)

    def count(block: pa.Table) -> pa.Table:
        xyz = np.stack([block.column(a).to_numpy() for a in "xyz"], axis=1)
        home = block.column("home").to_numpy(zero_copy_only=False)
        return pa.table([pa.array(block.column("pid").to_numpy()[home]), pa.array(np_count(xyz, home, kernel, r))], names=["cid", "n"])

    found = placed.groupBy("bx", "by", "bz").applyInArrow(count, "cid long, n long")
    return found.unionByName(cloud.filter(~sound).select(F.col("pid").alias("cid"), F.lit(0).cast("long").alias("n")))


def np_count(xyz: np.ndarray, asked: np.ndarray, kernel: Kernel, r: float) -> np.ndarray:
    """How many rows lie within the kernel around each asked one. Coincident rows are one with a weight; the others are
    tested by cells of a quarter of the radius, in runs along the last axis."""
    if not asked.any():
        return np.zeros(0, np.int64)
    side, span = r / 4, 5
    cell = np.floor((xyz - xyz.min(axis=0)) / side).astype(np.int64)
    cell[:, kernel.dims :] = 0
    order = np.lexsort((*xyz.T[::-1], *cell.T[::-1]))
    points, cell = xyz[order], cell[order]
    new = np.concatenate(([True], (points[1:] != points[:-1]).any(axis=1)))
    which = np.cumsum(new) - 1
    first = np.flatnonzero(new)
    points, cell, weight = points[first], cell[first], np.diff(np.append(first, len(new)))
    wanted = np.bincount(which[asked[order]], minlength=len(points)) > 0
    # one number for a cell, such that a run along the last axis is a run of numbers
    size = cell.max(axis=0) + 2 * span + 1
    number = ((cell[:, 0] + span) * size[1] + cell[:, 1] + span) * size[2] + cell[:, 2] + span
    o = np.arange(-span, span + 1)
    ox, oy = (x.ravel() for x in np.meshgrid(o, o if kernel.dims > 1 else [0], indexing="ij"))
    gap = lambda x: np.maximum(np.abs(x) - 1, 0) * side
    near = lambda x, y, z: kernel.np_hits(np.stack(np.broadcast_arrays(gap(x), gap(y), gap(z)), -1).reshape(-1, 3).astype(float), np.zeros((1, 3)), np.array([r * (1 + 1e-9)]))
    far = np.stack([near(ox, oy, z) for z in range(span + 1)]).sum(axis=0) - 1  # how far the run goes to each side
    if kernel.dims < 3:
        far = np.minimum(far, 0)
    ox, oy, far = ox[far >= 0], oy[far >= 0], far[far >= 0]
    column = (ox * size[1] + oy) * size[2]
    counts, columns = np.zeros(len(points), np.int64), [np.ascontiguousarray(x) for x in points.T[: kernel.dims]]
    starts = np.flatnonzero(np.concatenate(([True], number[1:] != number[:-1])))
    for lo, hi in zip(starts.tolist(), np.append(starts[1:], len(number)).tolist(), strict=True):
        some = lo + np.flatnonzero(wanted[lo:hi])
        if not len(some):
            continue
        begin, end = np.searchsorted(number, number[lo] + column - far), np.searchsorted(number, number[lo] + column + far, side="right")
        rows = spread(begin, end - begin)
        there, heavy = [x[rows] for x in columns], weight[rows].astype(np.float64)
        at_once, alone = max(1, (1 << 17) // max(1, len(rows))), not (weight[rows] > 1).any()
        for i in range(0, len(some), at_once):
            own = some[i : i + at_once]
            hit = _within(there, [x[own, None] for x in columns], kernel, r)
            counts[own] = np.count_nonzero(hit, axis=1) if alone else (hit.astype(np.float64) @ heavy).astype(np.int64)
    out = np.zeros(len(order), np.int64)
    out[order] = counts[which]
    return out[asked]


def _within(p: list[np.ndarray], q: list[np.ndarray], kernel: Kernel, r: float) -> np.ndarray:
    """``Kernel.np_hits`` of all rows against all, axis by axis."""
    gaps = [a - b for a, b in zip(p, q, strict=True)]
    if not kernel.round:
        return np.logical_and.reduce([np.abs(g) < r for g in gaps])
    total = gaps[0] * gaps[0]
    for g in gaps[1:]:
        total += g * g
    return total < r * r


def isolated_points(cloud: DataFrame, grid, r: float) -> DataFrame:
    """Points without another within r."""
    pairs = radius_gridjoin(cloud, all_centres(cloud), SPHERE, r, grid).filter("cid <> pid")
    return cloud.select("pid").join(pairs.select(F.col("cid").alias("pid")), "pid", "left_anti")


def local_moments(pairs: DataFrame, cloud: DataFrame) -> DataFrame:
    """(cid, n, means, covariances xx .. zz) of each neighbourhood, by one aggregation."""
    joined = pairs.select("cid", "pid").join(cloud.select("pid", "x", "y", "z"), "pid")
    cov = [F.covar_pop(a, b).alias(f"c{a}{b}") for i, a in enumerate("xyz") for b in "xyz"[i:]]
    return joined.groupBy("cid").agg(F.count("*").alias("n"), *(F.avg(a).alias(f"m{a}") for a in "xyz"), *cov)


def shape(moments: DataFrame) -> DataFrame:
    """(cid, nx, ny, nz, linearity, planarity, sphericity) from the eigenvalues of each covariance."""
    names = ["nx", "ny", "nz", "linearity", "planarity", "sphericity"]

    @F.pandas_udf(", ".join(f"{n} double" for n in names))
    def solve(xx: pd.Series, xy: pd.Series, xz: pd.Series, yy: pd.Series, yz: pd.Series, zz: pd.Series) -> pd.DataFrame:
        m = np.stack([np.stack([xx, xy, xz], -1), np.stack([xy, yy, yz], -1), np.stack([xz, yz, zz], -1)], -2)
        values, vectors = np.linalg.eigh(m)
        low, mid, top = values.T
        safe = np.where(top > 0, top, 1.0)
        normal = vectors[:, :, 0]
        return pd.DataFrame(dict(zip(names, [*normal.T, (top - mid) / safe, (mid - low) / safe, low / safe], strict=True)))

    return moments.select("cid", solve("cxx", "cxy", "cxz", "cyy", "cyz", "czz").alias("s")).select("cid", *(F.col(f"s.{n}").alias(n) for n in names))


def radius_components(cloud: DataFrame, grid, r: float, rounds: int = 50) -> DataFrame:
    """(pid, component): smallest id reachable by steps shorter than r. Labels spread and jump to their label's label; raises if ``rounds`` don't suffice."""
    pairs = radius_gridjoin(cloud, all_centres(cloud), SPHERE, r, grid).filter("cid <> pid")
    edges = materialise(pairs, "component-edges")
    labels = materialise(cloud.select("pid", F.col("pid").alias("label")), "labels")
    for _ in range(rounds):
        seen = edges.join(labels, "pid").groupBy(F.col("cid").alias("pid")).agg(F.min("label").alias("near"))
        lower = labels.join(seen, "pid", "left").select("pid", F.least("label", "near").alias("label"), F.col("label").alias("was"))
        jump = lower.select(F.col("pid").alias("label"), F.col("label").alias("root"))
        new = materialise(lower.join(jump, "label").select("pid", F.col("root").alias("label"), "was"), "labels")
        if new.filter("label <> was").isEmpty():
            return new.select("pid", F.col("label").alias("component"))
        labels = new.select("pid", "label")
    raise RuntimeError("components did not settle; allow more rounds")


def shared_neighbours(pairs: DataFrame, ranked: DataFrame) -> DataFrame:
    """(i, shared): neighbours that a centre has in common with the next centre in order."""
    placed = pairs.join(ranked.select(F.col("pid").alias("cid"), F.col("idx").alias("i")), "cid").select("i", "pid")
    following = placed.select((F.col("i") - 1).alias("i"), "pid")
    return placed.join(following, ["i", "pid"]).groupBy("i").agg(F.count("*").alias("shared"))
