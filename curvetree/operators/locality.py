"""How local an ordering is: histograms of index gaps between nearest neighbours, their moments and quartiles, proxies for cache misses."""

from __future__ import annotations

import math
from collections import OrderedDict
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import GridSpec, fit_grid
from ..plans.ranks import global_rank
from ..sources.clouds import original_rank, share_of_centres
from ..session import discard, materialise
from .reorder import Index, build_index, rank_only
from .tiles import knn_lists


def ranks(cloud: DataFrame, grid: GridSpec, curves: tuple[str, ...] = ("none", "morton", "hilbert")) -> DataFrame:
    """(pid, curve, idx) for each ordering."""
    out = None
    for c in curves:
        part = (original_rank(cloud).select("pid", "idx") if c == "none" else rank_only(cloud, c, grid)).select("pid", F.lit(c).alias("curve"), "idx")
        out = part if out is None else out.union(part)
    return out


def neighbour_ranks(index: Index, cloud: DataFrame, centres: DataFrame, k: int, grid: GridSpec, curves: tuple[str, ...] = ("none", "morton", "hilbert")) -> DataFrame:
    """(curve, cid, i, pid, j): a row for each centre and ordering, with arrays of its neighbours and their ranks.

    Ranks go with the points into the search, so pairs are never joined, shuffled or stored one by one. ``grid`` is that of
    the orderings, the index may have its own."""
    wide, names = None, tuple(f"rank_{c}" for c in curves)
    for c, name in zip(curves, names, strict=True):
        own = (original_rank(cloud) if c == "none" else rank_only(cloud, c, grid)).select("pid", F.col("idx").alias(name))
        wide = own if wide is None else wide.join(own, "pid")
    wide = materialise(wide, "ranks")
    points = materialise(index.points.join(wide, "pid"), "ranked-points", by="part" if index.parts > 1 else None)
    found = knn_lists(replace(index, points=points), centres, k, carry=names)
    own = wide.select(F.col("pid").alias("cid"), *(F.col(n).alias(f"own_{n}") for n in names))
    found = materialise(found.join(own, "cid"), "neighbour-ranks")
    each = F.explode(F.array(*(F.struct(F.lit(c).alias("curve"), F.col(f"own_{n}").alias("i"), F.col(n).alias("j")) for c, n in zip(curves, names, strict=True))))
    return found.select("cid", "pid", each.alias("s")).select("s.curve", "cid", "s.i", "pid", "s.j")


def neighbour_gaps(index: Index, cloud: DataFrame, centres: DataFrame, k: int, grid: GridSpec, curves: tuple[str, ...] = ("none", "morton", "hilbert")) -> DataFrame:
    """(curve, d, n, h): of the searches of ``neighbour_ranks``, how many centres have ``n`` neighbours at gap ``d``.

    Gaps are counted where the lists are found, so neither lists nor pairs are stored. Centres are points of the cloud, so
    each is the first of its own neighbours and its ranks are at hand. The index's points are the cloud's, so these are ranked."""
    names, points, last = tuple(f"rank_{c}" for c in curves), index.points, None
    for c, name in zip(curves, names, strict=True):
        # all columns go through the sort, so ranks need no join
        coded = points if c == "none" else encode(points.withColumnRenamed("code", "__code"), grid, c).drop("cx", "cy", "cz")
        ranked = global_rank(coded, ["pid"] if c == "none" else ["code", "pid"], name)
        points = ranked if c == "none" else ranked.drop("code").withColumnRenamed("__code", "code")
        if last is not None:
            discard(last)
        last = ranked
    if index.parts > 1:
        points = materialise(points, "ranked-points", by="part")
        discard(last)
        last = points
    counted = knn_lists(replace(index, points=points), centres, k, carry=names, fold=count_gaps, folded="at int, d long, n long, h long")
    total = materialise(counted.groupBy("at", "d", "n").agg(F.sum("h").alias("h")), "gaps")
    discard(last)
    return total.select(F.element_at(F.array(*map(F.lit, curves)), F.col("at") + 1).alias("curve"), "d", "n", "h")


def count_gaps(first: np.ndarray, ranked: list[np.ndarray]) -> pa.RecordBatch:
    """(at, d, n, h) of many centres' lists of ranks: the ordering's number, and how many centres have n neighbours at gap d."""
    out: list[list[np.ndarray]] = [[], [], [], []]
    for at, rank in enumerate(ranked if len(first) else []):
        size = np.diff(np.append(first, len(rank)))
        gap = np.abs(rank - np.repeat(rank[first], size))
        wide = int(gap.max()) + 1
        held, n = np.unique(np.repeat(np.arange(len(first)), size) * wide + gap, return_counts=True)
        each = held % wide * (int(n.max()) + 1) + n
        each, h = np.unique(each, return_counts=True)
        for x, y in zip(out, (np.full(len(each), at, np.int32), each // (int(n.max()) + 1), each % (int(n.max()) + 1), h), strict=True):
            x.append(y)
    kinds = (np.int32, np.int64, np.int64, np.int64)
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate([*x, np.zeros(0, t)]).astype(t)) for x, t in zip(out, kinds, strict=True)], names=["at", "d", "n", "h"])


def list_gaps(listed: DataFrame) -> DataFrame:
    """(curve, cid, i, j, d) of each neighbour, from the rows of ``neighbour_ranks``."""
    return listed.select("curve", "cid", "i", F.explode("j").alias("j")).withColumn("d", F.abs(F.col("i") - F.col("j")))


def knn_gaps(knn: DataFrame, ranked: DataFrame) -> DataFrame:
    """(curve, cid, pid, i, j, d): neighbours are the same under every order, so they are found once and ranked by each."""
    i = ranked.select(F.col("pid").alias("cid"), "curve", F.col("idx").alias("i"))
    j = ranked.select("pid", "curve", F.col("idx").alias("j"))
    return knn.select("cid", "pid").join(i, "cid").join(j, ["pid", "curve"]).withColumn("d", F.abs(F.col("i") - F.col("j")))


def gap_multiplicity(gaps: DataFrame) -> DataFrame:
    """How often a centre has a neighbour at each gap: 1 at most for gap 0, 2 for others."""
    return gaps.groupBy("curve", "i", "d").agg(F.count("*").alias("n"))


def histogram(gaps: DataFrame, include_self: bool = True) -> DataFrame:
    """``gaps``: a row for each pair, or those of ``neighbour_gaps``."""
    pairs = F.sum(F.col("n") * F.col("h")) if "h" in gaps.columns else F.count("*")
    return (gaps if include_self else gaps.filter("d > 0")).groupBy("curve", "d").agg(pairs.alias("h"))


def skewness(hist: DataFrame) -> DataFrame:
    """(curve, n_pairs, g1): population skewness from exact power sums, turned to double at the end."""
    d, h = F.col("d").cast("decimal(38,0)"), F.col("h").cast("decimal(38,0)")
    s = hist.groupBy("curve").agg(F.sum("h").alias("n_pairs"), F.sum(d * h).cast("double").alias("s1"), F.sum(d * d * h).cast("double").alias("s2"), F.sum(d * d * d * h).cast("double").alias("s3"))
    n, m = F.col("n_pairs").cast("double"), F.col("s1") / F.col("n_pairs")
    var = F.col("s2") / n - m * m
    third = F.col("s3") / n - F.lit(3.0) * m * F.col("s2") / n + F.lit(2.0) * m * m * m
    return s.select("curve", "n_pairs", F.round(third / (var * F.sqrt(var)), 6).alias("g1"))


def quartiles(hist: DataFrame, shares: tuple[float, ...] = (0.25, 0.5, 0.75)) -> DataFrame:
    """The smallest gap whose running count reaches each share, rounded up. One row for each distinct gap is summed in order, per curve."""
    run = Window.partitionBy("curve").orderBy("d")
    cum = hist.withColumns({"c": F.sum("h").over(run), "n": F.sum("h").over(Window.partitionBy("curve"))})
    return cum.groupBy("curve").agg(*(F.min(F.when(F.col("c") >= F.ceil(F.lit(p) * F.col("n")), F.col("d"))).alias(f"q{i + 1}") for i, p in enumerate(shares)))


def summary(hist: DataFrame) -> DataFrame:
    return quartiles(hist).join(skewness(hist), "curve").select("curve", "q1", "q2", "q3", "g1", "n_pairs")


def log_bins(hist: DataFrame) -> DataFrame:
    return hist.groupBy("curve", F.when(F.col("d") == 0, -1).otherwise(F.floor(F.log2("d"))).cast("int").alias("bin")).agg(F.sum("h").alias("h"))


def check_histogram(hist: DataFrame, n: int, k: int) -> DataFrame:
    """(curve, ok): every point finds itself, and all find min(k, n)."""
    sums = hist.groupBy("curve").agg(F.sum(F.when(F.col("d") == 0, F.col("h")).otherwise(0)).alias("own"), F.sum("h").alias("all"))
    return sums.select("curve", ((F.col("own") == n) & (F.col("all") == n * min(k, n))).alias("ok"))


def locality(cloud: DataFrame, k: int = 50, share: float | None = None, curves: tuple[str, ...] = ("none", "morton", "hilbert"), bucket: int = 128, tile_points: int = 4_000_000) -> DataFrame:
    """Histograms of all orderings from one neighbour search, over all centres or a share of them; neighbours from the whole cloud."""
    grid = fit_grid(cloud)
    index = build_index(cloud, "hilbert", bucket, tile_points, fit_grid(cloud, box="cubic"))
    return histogram(neighbour_gaps(index, cloud, share_of_centres(index.points, 1.0 if share is None else share), k, grid, curves))


def recommend_curve(cloud: DataFrame, k: int = 50, share: float = 0.01) -> DataFrame:
    """The orderings by sampled skewness, best first: a few rows."""
    return summary(locality(cloud, k, share)).orderBy(F.desc("g1"), "curve")


def null_model(n: int) -> dict[str, float]:
    """What a random order gives: gaps follow a triangular law."""
    return {"g1": 2 * math.sqrt(2) / 5, **{f"q{i}": n * (1 - math.sqrt(1 - i / 4)) for i in (1, 2, 3)}}


def blocks_touched(gaps: DataFrame, block: int = 2) -> DataFrame:
    """(curve, blocks): distinct storage blocks that a neighbourhood touches, on average; stands in for misses of a real cache.
    ``gaps``: a row for each pair, or those of ``neighbour_ranks``."""
    if dict(gaps.dtypes)["j"].startswith("array"):
        per = gaps.select("curve", F.size(F.array_distinct(F.expr(f"transform(j, x -> x div {block})"))).alias("b"))
    else:
        per = gaps.groupBy("curve", "cid").agg(F.countDistinct(F.expr(f"j div {block}")).alias("b"))
    return per.groupBy("curve").agg(F.round(F.avg("b"), 6).alias("blocks"))


def lru_misses(gaps: DataFrame, lines: int = 512, line_points: int = 2, chunk: int = 65_536) -> DataFrame:
    """(curve, misses per centre) of a simulated least-recently-used cache, centres in order. Each chunk of centres starts cold."""

    def simulate(pdf: pd.DataFrame) -> pd.DataFrame:
        cache: OrderedDict[int, None] = OrderedDict()
        misses = 0
        pdf = pdf.sort_values(["i", "j"])
        for line in (pdf["j"].to_numpy() // line_points).tolist():
            if line in cache:
                cache.move_to_end(line)
            else:
                misses += 1
                cache[line] = None
                if len(cache) > lines:
                    cache.popitem(last=False)
        return pd.DataFrame({"curve": [pdf["curve"].iloc[0]], "misses": [misses], "centres": [pdf["i"].nunique()]})

    parts = gaps.select("curve", "i", "j", F.expr(f"i div {chunk}").alias("c")).groupBy("curve", "c").applyInPandas(simulate, "curve string, misses long, centres long")
    return parts.groupBy("curve").agg((F.sum("misses") / F.sum("centres")).alias("misses_per_centre"))


def write_histogram(hist: DataFrame, path: str) -> None:
    """Delimited text with a header: curve, d, h, by curve and gap. One row for each distinct gap."""
    hist.select("curve", "d", "h").repartitionByRange("curve", "d").sortWithinPartitions("curve", "d").write.csv(path, header=True)


def agreement(full: DataFrame, sampled: DataFrame) -> DataFrame:
    """(curve, g1, g1_sample, error): the sample's skewness against the whole cloud's."""
    return full.select("curve", "g1").join(sampled.select("curve", F.col("g1").alias("g1_sample")), "curve").withColumn("error", F.abs(F.col("g1_sample") - F.col("g1")) / F.abs("g1"))


def np_skewness(d: np.ndarray) -> float:
    c = d - d.mean()
    return float((c**3).mean() / (c**2).mean() ** 1.5)
