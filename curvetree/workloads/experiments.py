"""W1 to W20. Each takes a Bench and returns rows (dicts) of parameters and measures; times are of this machine.

Arms that the defaults name ``None`` centres for are full searches: every point is a centre, in the order of the index.
"""

from __future__ import annotations

import subprocess
import sys
import time
from collections.abc import Callable, Iterable
from functools import cache
from itertools import product

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.curves import encode
from ..functions.grid import fit_grid
from ..functions.kernels import KERNELS, SPHERE
from ..operators import costs, locality
from ..operators.local import COUNTERS, LINEAR, STRUCTURES, LinearOctree, PointerTree, Walk
from ..operators.octree import build_tree, octants
from ..operators.relational import radius_gridjoin
from ..operators.reorder import Index, build_index, jump_profile, reorder
from ..operators.sizes import bytes_held, count_nodes
from ..operators.tiles import knn_tiles, radius_tiles
from ..sources import clouds

OWN = ("pointer", "leafscan", "prune", "ranges")
BASELINES = ("noncomplete", "resolution", "kd_small", "kd_ten", "kd_sliding")
CURVES = ("none", "morton", "hilbert")
#: the five pairs of structure and order that are compared
CONFIGURATIONS = (("pointer", "none"), ("pointer", "morton"), ("pointer", "hilbert"), ("leafscan", "morton"), ("leafscan", "hilbert"))
ENTRY_BYTES = {"ranges": 16, "indices": 8, "coords": 24}
Row = dict


class Bench:
    """Clouds and indexes of one folder, made once each."""

    def __init__(self, spark: SparkSession, sf_dir: str, tile_points: int = 50_000, runs: int = 1):
        self.spark, self.dir, self.tile_points, self.runs = spark, sf_dir, tile_points, runs
        self.cloud = cache(lambda name: clouds.load(spark, sf_dir, name).cache())
        self.index = cache(self._index)
        self.cube = cache(self._cube)
        self.xyz = cache(self._xyz)
        self.nodes = cache(lambda name, structure: count_nodes(clouds.load(spark, sf_dir, name), fit_grid(self.cloud(name)), structure))
        self.points = cache(lambda name: clouds.load(spark, sf_dir, name).count())

    def _index(self, name: str, curve: str = "hilbert", bucket: int = 128) -> Index:
        return build_index(self.cloud(name), curve, bucket, self.tile_points)

    def _cube(self, name: str, curve: str = "hilbert") -> Index:
        """For nearest neighbours: a grid of cubes."""
        return build_index(self.cloud(name), curve, 128, self.tile_points, fit_grid(self.cloud(name), box="cubic"))

    def _xyz(self, name: str, curve: str) -> tuple[np.ndarray, np.ndarray]:
        """A cloud on the driver in an order, for measures of single structures (clouds of tests only)."""
        grid = fit_grid(self.cloud(name))
        p = encode(self.cloud(name), grid, "hilbert" if curve == "none" else curve).orderBy(*(["pid"] if curve == "none" else ["code", "pid"])).select("x", "y", "z", "code").toPandas()
        return p[["x", "y", "z"]].to_numpy(), p["code"].to_numpy()

    def centres(self, name: str, n: int | None, index: Index | None = None) -> DataFrame:
        """``n`` points of smallest hash; None: all, in the order of the index."""
        if n is None:
            return clouds.all_centres(index.points if index else self.cloud(name))
        return clouds.sample_centres(self.cloud(name), n)

    def radius(self, name: str, structure: str, kernel: str, r: float, n: int | None, curve: str = "hilbert", bucket: int = 128, output: str | None = None) -> Row:
        """One search: mean neighbours, seconds, work, and the size of the result."""
        index = self.index(name, curve, bucket)
        q = self.centres(name, n, index)
        seconds, facts, form = 0.0, None, None
        for _ in range(self.runs):
            began = time.perf_counter()
            found = radius_tiles(index, q, KERNELS[kernel], r, structure, cell=max(index.grid.ext) / 16, output=output)
            form = next((f for f in ENTRY_BYTES if f in found.columns), None)
            entries = F.sum(F.size(form)) if form else F.lit(0)
            facts = found.agg(F.sum("n"), entries, F.sum("pid_sum"), *(F.sum(c) for c in COUNTERS)).first()
            seconds += time.perf_counter() - began
        size = max(1, q.count())
        work = {c: float(v or 0) / size for c, v in zip(COUNTERS, facts[3:], strict=True)}
        total, listed = int(facts[0] or 0), int(facts[1] or 0)
        return {"cloud": name, "structure": structure, "kernel": kernel, "r": r, "curve": curve, "bucket": bucket, "centres": size, "n": total, "pid_sum": int(facts[2] or 0), "mu": total / size, "seconds": seconds / self.runs, "form": form, "entries": listed, "bytes": listed * ENTRY_BYTES.get(form, 0), **work}

    def knn(self, name: str, structure: str, k: int, n: int | None, curve: str = "hilbert") -> Row:
        index = self.cube(name, curve)
        q, out, seconds = self.centres(name, n, index), None, 0.0
        for _ in range(self.runs):
            began = time.perf_counter()
            out = knn_tiles(index, q, k, structure, cell=max(index.grid.ext) / 16).agg(F.count("*"), F.sum("pid")).first()
            seconds += time.perf_counter() - began
        return {"cloud": name, "structure": structure, "k": k, "curve": curve, "centres": "all" if n is None else str(n), "pairs": out[0], "pid_sum": int(out[1] or 0), "seconds": seconds / self.runs}


def w1(b: Bench, names: Iterable[str] = ("event", "order"), radii: Iterable[float] = (10.0, 25.0, 50.0)) -> list[Row]:
    return [b.radius(c, "ranges", k, r, None) for c, k, r in product(names, KERNELS, radii)]


def w2(b: Bench, n: int = 5000, name: str = "ship", radii: Iterable[float] = (50.0, 100.0, 200.0)) -> list[Row]:
    return [b.radius(name, "ranges", k, r, n) for k, r in product(KERNELS, radii)]


def w3(b: Bench, n: int = 500, names: Iterable[str] = tuple(clouds.SPECS), kernels: Iterable[str] = tuple(KERNELS), radii: Iterable[float] = (50.0, 200.0)) -> list[Row]:
    return [b.radius(c, s, k, r, n, curve) for c, (s, curve), k, r in product(names, CONFIGURATIONS, kernels, radii)]


def w4(b: Bench, n: int = 500, names: Iterable[str] = tuple(clouds.SPECS), radii: Iterable[float] = (25.0, 50.0, 100.0, 200.0)) -> list[Row]:
    return [b.radius(c, s, "sphere", r, n) for c, s, r in product(names, OWN, radii)]


def w5(b: Bench, n: int | None = None, names: Iterable[str] = ("ship", "order", "event"), radii: Iterable[float] = (50.0, 200.0), buckets: Iterable[int] = (128, 16)) -> list[Row]:
    return [b.radius(c, s, "sphere", r, n, bucket=size) for c, s, r, size in product(names, OWN, radii, buckets)]


def w6(b: Bench, k: int = 50, names: Iterable[str] = ("ship", "part")) -> list[Row]:
    return [{"cloud": name, **r.asDict()} for name in names for r in locality.log_bins(locality.locality(b.cloud(name), k)).collect()]


def w7(b: Bench, k: int = 50, names: Iterable[str] = tuple(clouds.SPECS), shares: Iterable[float] = (1.0, 0.01, 0.001)) -> list[Row]:
    out = []
    for name in names:
        cloud, grid = b.cloud(name), fit_grid(b.cloud(name))
        ranked = locality.ranks(cloud, grid).cache()
        for share in shares:
            q = clouds.share_of_centres(cloud, share)
            if q.isEmpty():
                continue
            gaps = locality.knn_gaps(knn_tiles(b.cube(name), q, k), ranked).cache()
            blocks = {r["curve"]: r["blocks"] for r in locality.blocks_touched(gaps).collect()}
            lru = {r["curve"]: r["misses_per_centre"] for r in locality.lru_misses(gaps).collect()}
            for r in locality.summary(locality.histogram(gaps)).collect():
                out.append({"cloud": name, "share": share, **r.asDict(), "blocks": blocks[r["curve"]], "lru_misses": lru[r["curve"]]})
            gaps.unpersist()
    return out


def w8(b: Bench, n: int = 500, names: Iterable[str] = ("order", "event"), radii: Iterable[float] = (50.0, 200.0)) -> list[Row]:
    out = [b.radius(c, s, "sphere", r, n) for c, s, r in product(names, (*OWN, *BASELINES), radii)]
    for c, r in product(names, radii):
        grid, q = fit_grid(b.cloud(c)), b.centres(c, n)
        began = time.perf_counter()
        total = radius_gridjoin(b.cloud(c), q, SPHERE, r, grid).agg(F.count("*"), F.sum("pid")).first()
        out.append({"cloud": c, "structure": "gridjoin", "kernel": "sphere", "r": r, "n": total[0], "pid_sum": int(total[1] or 0), "seconds": time.perf_counter() - began})
    return out


def local_structure(b: Bench, name: str, structure: str, curve: str, bucket: int = 128) -> tuple[Walk, np.ndarray]:
    """A single structure over the whole cloud in one order, on the driver."""
    xyz, codes = b.xyz(name, curve)
    grid = fit_grid(b.cloud(name))
    if structure in LINEAR:
        return LinearOctree(xyz, codes, grid, curve, bucket), xyz
    box = (np.array(grid.lo), np.array(grid.lo) + np.array(grid.ext))
    return PointerTree(xyz, box, **({"bucket": bucket, "cell": max(grid.ext) / 16} | STRUCTURES[structure])), xyz


def _local_seconds(b: Bench, name: str, structure: str, curve: str, r: float, n: int | None) -> float:
    """A search in a single structure, centres in the cloud's order too."""
    tree, xyz = local_structure(b, name, structure, curve)
    q = xyz if n is None else xyz[np.sort(np.random.default_rng(7).choice(len(xyz), min(n, len(xyz)), replace=False))]
    began = time.perf_counter()
    (tree.radius if structure == "ranges" else tree.hits)(SPHERE, q, np.full(len(q), r), structure)
    return time.perf_counter() - began


def _order_effect(b: Bench, base: str, changed: str, structures: tuple[str, ...], n: int) -> list[Row]:
    out = []
    for name, s, sets in product(("order", "event"), structures, (n, None)):
        a, z = (_local_seconds(b, name, s, c, 100.0, sets) for c in (base, changed))
        out.append({"cloud": name, "structure": s, "centres": sets or "all", "base": base, "changed": changed, "base_seconds": a, "seconds": z, "relative": costs.relative_runtime(z, a)})
    return out


def w9(b: Bench, n: int = 300) -> list[Row]:
    return _order_effect(b, "none", "hilbert", ("pointer", *BASELINES), n)


def w10(b: Bench, n: int = 300) -> list[Row]:
    return _order_effect(b, "morton", "hilbert", (*OWN, *BASELINES), n)


def w11(b: Bench, n: int = 200, names: Iterable[str] = ("ship", "event"), sizes: Iterable[int] = (1, 10, 50, 100, 300, 500), sets: tuple[int | None, ...] = (0, None)) -> list[Row]:
    """``sets``: 0 stands for the n sampled centres, None for all."""
    return [b.knn(c, s, k, n if some == 0 else some) for some, c, s, k in product(sets, names, ("prune", "resolution", "kd_small", "kd_ten", "kd_sliding"), sizes)]


def w12(b: Bench, cores: tuple[int, ...] = (1, 2, 4, 8), radii: tuple[float, ...] = (50.0, 200.0), name: str = "ship", sets: tuple[int | None, ...] = (2000, None)) -> list[Row]:
    """Sessions of 1, 2, ... cores, each in a process of its own."""
    out = []
    for structure, r, n in product(("ranges", "kd_ten"), radii, sets):
        seconds = {}
        for p in cores:
            done = subprocess.run([sys.executable, "-m", "curvetree.workloads", "--cores", str(p), "--sf-dir", b.dir, "--one", f"{name}:{structure}:{r}:{n or 'all'}"], capture_output=True, text=True, check=True)
            seconds[p] = float(done.stdout.strip().splitlines()[-1])
        efficiency, gain = costs.parallel_efficiency(seconds), costs.speed_up(seconds)
        out += [{"cloud": name, "structure": structure, "r": r, "centres": n or "all", "cores": p, "seconds": seconds[p], "efficiency": efficiency[p], "speed_up": gain[p]} for p in cores]
    return out


MADE = {"linear octree": "ranges", "pointer octree": "pointer", "non-complete octree": "noncomplete", "octree by resolution": "resolution", "kd-tree, leaf 10": "kd_ten", "kd-tree, leaf 1": "kd_small"}


def w13(b: Bench, names: Iterable[str] = ("order", "event", "part")) -> list[Row]:
    """Bytes of the arrays that each structure holds, and their share of the cloud's. Nodes are counted by tasks."""
    out = []
    for name, (label, structure) in product(names, MADE.items()):
        nodes, points = b.nodes(name, structure), b.points(name)
        held = {label: bytes_held(structure, nodes, points)}
        if structure == "ranges":
            held["linear octree without boxes"] = bytes_held(structure, nodes, points, boxes=False)
        out += [{"cloud": name, "structure": k, "nodes": nodes, "points": points, "bytes": v, "overhead": v / (points * costs.POINT_BYTES)} for k, v in held.items()]
    return out


def w14(b: Bench, names: Iterable[str] = ("order", "event", "part")) -> list[Row]:
    """What is measured against the model: with the published bytes of a node, and with those of this library's arrays."""
    out = []
    for name in names:
        for label in costs.LAYOUT_BYTES:
            nodes, points = b.nodes(name, MADE[label]), b.points(name)
            rho = nodes / points
            row = {"cloud": name, "structure": label, "rho": rho, "measured": bytes_held(MADE[label], nodes, points) / (points * costs.POINT_BYTES), "model": costs.expected_overhead(*costs.LAYOUT_BYTES[label], rho)}
            out.append(row | {"published_model": costs.expected_overhead(*costs.STRUCTURE_BYTES[label], rho)})
    return out


def w15(b: Bench, names: Iterable[str] = ("order", "ship")) -> list[Row]:
    out = []
    for name in names:
        grid = fit_grid(b.cloud(name))
        coded = encode(b.cloud(name), grid, "hilbert").select("code").cache()
        coded.count()
        for method in ("blocks", "iterative"):
            began = time.perf_counter()
            nodes = build_tree(coded, 128, 21, method=method).count()
            out.append({"cloud": name, "structure": f"linear octree, Spark, {method}", "nodes": nodes, "seconds": time.perf_counter() - began})
        b.xyz(name, "hilbert")
        for label, structure in MADE.items():
            began = time.perf_counter()
            tree, _ = local_structure(b, name, structure, "hilbert")
            out.append({"cloud": name, "structure": f"{label}, one process", "nodes": len(tree.lo), "seconds": time.perf_counter() - began})
        coded.unpersist()
    return out


def w16(b: Bench, n: int = 300, names: Iterable[str] = ("order", "event"), buckets: Iterable[int] = (16, 32, 64, 128, 256)) -> list[Row]:
    return [b.radius(c, "prune", "sphere", 200.0, n, bucket=size) for c, size in product(names, buckets)]


def w17(b: Bench, names: Iterable[str] = tuple(clouds.SPECS), shares: Iterable[float] = (0.1, 0.01)) -> list[Row]:
    out = []
    for name in names:
        full = {r["curve"]: r["g1"] for r in locality.recommend_curve(b.cloud(name), 50, 1.0).collect()}
        for share in shares:
            some = {r["curve"]: r["g1"] for r in locality.recommend_curve(b.cloud(name), 50, share).collect()}
            if some:
                out.append({"cloud": name, "share": share, "choice": max(some, key=some.get), "full_choice": max(full, key=full.get), "error": abs(max(some.values()) - full[max(some, key=some.get)]) / full[max(some, key=some.get)]})
    return out


def w18(b: Bench) -> list[Row]:
    tree = build_tree(encode(b.cloud("text"), fit_grid(b.cloud("text")), "morton"), 16, 21)
    return [r.asDict() for r in octants(tree, 5).orderBy("level", "prefix").collect()]


def w19(b: Bench, names: Iterable[str] = ("order", "event", "part")) -> list[Row]:
    out = []
    for name, curve in product(names, CURVES):
        q = jump_profile(reorder(b.cloud(name), curve)).agg(F.expr("percentile(jump, array(0.25, 0.5, 0.75, 1))")).first()[0]
        out.append({"cloud": name, "curve": curve, **dict(zip(("q1", "q2", "q3", "longest"), q, strict=True))})
    return out


def w20(b: Bench, n: int | None = 500, names: Iterable[str] = ("order", "event"), radii: Iterable[float] = (50.0, 200.0)) -> list[Row]:
    """The same traversal, run once for each form of its result."""
    return [b.radius(name, structure, "sphere", r, n, bucket=16, output=form) for name, r, (structure, form) in product(names, radii, (("ranges", "ranges"), ("prune", "indices"), ("prune", "coords")))]


WORKLOADS: dict[str, Callable[..., list[Row]]] = {f"W{i}": f for i, f in enumerate((w1, w2, w3, w4, w5, w6, w7, w8, w9, w10, w11, w12, w13, w14, w15, w16, w17, w18, w19, w20), 1)}
