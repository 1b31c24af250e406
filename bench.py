"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from curvetree.functions.curves import encode
from curvetree.functions.grid import fit_grid
from curvetree.functions.kernels import SPHERE
from curvetree.operators import locality, relational, tiles
from curvetree.operators.octree import build_tree
from curvetree.operators.reorder import build_index
from curvetree.session import local_session
from curvetree.sources import clouds

SF_DIR, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), int(os.environ.get("BENCH_CPUS", "8"))


def main() -> None:
    spark = local_session(CPUS, CPUS, os.environ.get("BENCH_MEMORY", "8g"))
    took: dict[str, float] = {}

    def run(name: str, make) -> None:
        began = time.perf_counter()
        make()
        took[name] = round(time.perf_counter() - began, 3)

    def drop(df) -> None:
        df.write.format("noop").mode("overwrite").save()

    ship = clouds.load(spark, SF_DIR, "ship").cache()
    ship.count()
    grid = fit_grid(ship)
    drop(encode(ship.limit(10), grid, "hilbert"))  # starts the Python workers
    for curve in ("morton", "hilbert"):
        run(f"encode_{curve}", lambda curve=curve: drop(encode(ship, grid, curve)))
    kept = {}
    run("build_index", lambda: kept.update(index=build_index(ship, "hilbert", 128, 75_000, grid)))
    index = kept["index"]
    run("build_octree", lambda: build_tree(index.points, 128, 21).count())
    q, some = (clouds.sample_centres(ship, n).cache() for n in (5000, 500))
    q.count(), some.count()
    drop(tiles.radius_tiles(index, some, SPHERE, 50.0))  # warms the search up
    for r in (100, 200):
        for structure in ("leafscan", "prune", "ranges"):
            run(f"radius_{structure}_r{r}", lambda s=structure, r=r: drop(tiles.radius_tiles(index, q, SPHERE, float(r), s)))
    run("radius_prune_coords_r200", lambda: drop(tiles.radius_tiles(index, q, SPHERE, 200.0, "prune", output="coords")))
    for structure in ("pointer", "noncomplete", "kd_ten", "ranges"):
        run(f"radius_{structure}_r100_500", lambda s=structure: drop(tiles.radius_tiles(index, some, SPHERE, 100.0, s)))
    run("radius_gridjoin_r100", lambda: drop(relational.radius_gridjoin(ship, q, SPHERE, 100.0, grid)))
    order = clouds.load(spark, SF_DIR, "order")
    full = build_index(order, "hilbert", 128, 20_000)
    every = clouds.all_centres(full.points)
    for structure in ("pointer", "prune", "ranges"):
        run(f"radius_full_{structure}_order_r50", lambda s=structure: drop(tiles.radius_tiles(full, every, SPHERE, 50.0, s)))
    loose = build_index(order, "none", 128, 20_000)
    run("radius_full_pointer_none_order_r50", lambda: drop(tiles.radius_tiles(loose, clouds.all_centres(loose.points), SPHERE, 50.0, "pointer")))
    run("knn_k50_500", lambda: drop(tiles.knn_tiles(index, some, 50)))
    run("knn_k50_bestfirst_500", lambda: drop(tiles.knn_tiles(index, some, 50, method="bestfirst")))
    run("knn_k50_relational_500", lambda: drop(relational.knn_relational(ship, some, 50, grid)))
    run("curve_choice", lambda: locality.recommend_curve(clouds.load(spark, SF_DIR, "event"), 50, 0.01).collect())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF_DIR)}))


main()
