"""Both engines agree on results and work; edge clouds; plans; saved indexes; published figures."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvetree.functions.grid import fit_grid
from curvetree.functions.kernels import KERNELS, SPHERE, Kernel
from curvetree.operators import costs, locality, octree, relational, tiles
from curvetree.operators.reorder import build_index, load_index, save_index
from curvetree.plans.checks import plan_text, problems
from curvetree.queries import searches
from curvetree.sources import clouds

POINT = "pid long, x double, y double, z double"


@pytest.fixture(scope="module")
def event(spark, sf_dir):
    return clouds.load(spark, sf_dir, "event").cache()


def test_work_counters_agree(spark, sf_dir):
    a, b = (f(spark, sf_dir) for f in (searches.counters, searches.counters_by_arrays))
    costs.assert_same_set(a, b)
    assert a.agg(F.sum("contained")).first()[0] > 0


@pytest.mark.parametrize("rows", [[], [(0, 1.0, 2.0, 3.0)], [(i, 1.0, 1.0, 1.0) for i in range(40)], [(i, float(i), 0.0, 0.0) for i in range(40)]])
def test_edge_clouds(spark, rows):
    cloud = spark.createDataFrame(rows, POINT)
    centres = spark.createDataFrame([(0, 1.0, 2.0, 3.0), (1, 900.0, 0.0, 0.0)], "cid long, qx double, qy double, qz double")
    index = build_index(cloud, "hilbert", 4, 8)
    for r in (0.0, 2.5, 1e5):
        got = tiles.radius_summary(index, centres, tiles.radius_tiles(index, centres, SPHERE, r))
        costs.assert_same_set(got, relational.summarise(relational.radius_brute(cloud, centres, SPHERE, r), centres))
    got = tiles.knn_tiles(index, centres, 3).select("cid", "rank", "pid")
    costs.assert_same_set(got, relational.knn_brute(cloud, centres, 3).select("cid", "rank", "pid"))


def test_centres_outside_and_custom_kernel(spark, event):
    grid = fit_grid(event)
    q = clouds.lattice_centres(spark, grid)
    index = build_index(event, "morton", 16, 200)
    plain = Kernel("custom", 3, True, inside=False)
    for kernel in (*KERNELS.values(), plain):
        got = tiles.radius_summary(index, q, tiles.radius_tiles(index, q, kernel, 250.0))
        costs.assert_same_set(got, relational.summarise(relational.radius_brute(event, q, kernel, 250.0), q))
        costs.assert_same_set(relational.summarise(relational.radius_gridjoin(event, q, kernel, 250.0, grid), q), got)


def test_ranges_are_sorted_disjoint_and_same_under_shuffled_input(spark, event):
    q = clouds.sample_centres(event, 20)
    found = []
    for cloud in (event, event.orderBy(F.rand(3))):
        index = build_index(cloud, "hilbert", 16, 100)
        found.append(tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, 200.0), q))
    a, b = ({r["cid"]: (r["n"], [tuple(s) for s in r["ranges"]]) for r in f.collect()} for f in found)
    assert a == b
    for n, ranges in a.values():
        assert sum(hi - lo for lo, hi in ranges) == n and all(x[1] < y[0] for x, y in zip(ranges, ranges[1:], strict=False))


def test_tree_invariants(spark, event):
    index = build_index(event, "hilbert", 16, 10**9)
    rows = octree.build_tree(index.points, 16, 21).collect()
    by = {(r["level"], r["prefix"]): r for r in rows}
    assert sum(r["cnt"] for r in rows if r["is_leaf"]) == event.count()
    for (level, prefix), r in by.items():
        assert r["idx_hi"] - r["idx_lo"] == r["cnt"]
        if not r["is_leaf"]:
            kids = [by[level + 1, prefix * 8 + o] for o in range(8)]
            assert kids[0]["idx_lo"] == r["idx_lo"] and kids[-1]["idx_hi"] == r["idx_hi"]
            assert all(x["idx_hi"] == y["idx_lo"] for x, y in zip(kids, kids[1:], strict=False))
    assert by[0, 0]["code_hi"] == 2**63 - 1
    shapes = []
    for curve in ("morton", "hilbert"):
        t = octree.with_boxes(octree.build_tree(build_index(event, curve, 16, 10**9).points, 16, 21), index.grid, curve)
        shapes.append(sorted(tuple(r) for r in t.select("level", "cnt", "x0", "y0", "z0").collect()))
    assert shapes[0] == shapes[1]


def test_outputs_hold_the_same_neighbours(spark, event):
    """Ranges, indices and coordinates of one search; only what they list differs."""
    index, q = build_index(event, "hilbert", 16, 200), clouds.id_centres(event, 50)
    place = {r["idx"]: r for r in index.points.collect()}
    ranges = {r["cid"]: [i for s in r["ranges"] for i in range(s["lo"], s["hi"])] for r in tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, 200.0), q).collect()}
    for structure in ("prune", "leafscan", "pointer", "kd_ten"):
        found = tiles.radius_tiles(index, q, SPHERE, 200.0, structure)
        assert "ranges" not in found.columns
        assert {r["cid"]: r["indices"] for r in tiles.merge_lists(found, q).collect()} == ranges
    for structure, options in (("noncomplete", {}), ("prune", {"output": "coords"})):
        got = {r["cid"]: [tuple(c) for c in r["coords"]] for r in tiles.merge_lists(tiles.radius_tiles(index, q, SPHERE, 200.0, structure, **options), q).collect()}
        assert got == {c: sorted((place[i]["x"], place[i]["y"], place[i]["z"]) for i in ids) for c, ids in ranges.items()}
    counts = {r["cid"]: r["n"] for r in tiles.radius_tiles(index, q, SPHERE, 200.0, output="count").groupBy("cid").agg(F.sum("n").alias("n")).collect()}
    assert {c: counts.get(c, 0) for c in ranges} == {c: len(v) for c, v in ranges.items()}
    sizes = {s: tiles.output_bytes(tiles.radius_tiles(index, q, SPHERE, 200.0, s)).first() for s in ("ranges", "prune", "noncomplete")}
    assert sizes["prune"]["entries"] == sizes["prune"]["n"] == sizes["ranges"]["n"] > 3 * sizes["ranges"]["entries"]
    assert sizes["noncomplete"]["bytes"] == 3 * sizes["prune"]["bytes"]


def test_options(spark, event):
    index, q = build_index(event, "hilbert", 16, 200), clouds.id_centres(event, 20)
    own = {r["pid"]: r["idx"] for r in index.points.select("pid", "idx").collect()}
    plain = {r["cid"]: r["indices"] for r in tiles.neighbours(index, q, SPHERE, 100.0, "prune").collect()}
    without = {c: [i for i in v if i != own[c]] for c, v in plain.items()}
    got = tiles.neighbours(index, q, SPHERE, 100.0, "prune", exclude_self=True, limit=3).collect()
    assert {r["cid"]: (r["n"], r["indices"]) for r in got} == {c: (len(v), v[:3]) for c, v in without.items()}
    got = tiles.neighbours(index, q, SPHERE, 100.0, exclude_self=True, min_count=10).collect()
    assert {r["cid"]: [i for s in r["ranges"] for i in range(s["lo"], s["hi"])] for r in got} == {c: v for c, v in without.items() if len(v) >= 10}
    assert all(r["n"] == len(without[r["cid"]]) for r in got)


def test_unordered_cloud(spark, event):
    """Points keep the order of acquisition; structures that need a curve refuse."""
    index, q = build_index(event, "none", 16, 200), clouds.id_centres(event, 50)
    assert [r["idx"] for r in index.points.orderBy("pid").collect()] == list(range(event.count()))
    for structure in ("pointer", "resolution", "kd_sliding", "noncomplete"):
        got = tiles.radius_summary(index, q, tiles.radius_tiles(index, q, SPHERE, 150.0, structure, cell=60.0))
        costs.assert_same_set(got, relational.summarise(relational.radius_brute(event, q, SPHERE, 150.0), q))
    costs.assert_same_set(tiles.knn_tiles(index, q, 7, "pointer").select("cid", "rank", "pid"), relational.knn_brute(event, q, 7).select("cid", "rank", "pid"))
    with pytest.raises(ValueError):
        tiles.radius_tiles(index, q, SPHERE, 1.0, "ranges")
    with pytest.raises(ValueError):
        tiles.knn_tiles(index, q, 1)


def test_coincident_points_and_parts(spark, monkeypatch):
    """A cell of the last level is cut into tiles by rank; searches read the folders of their tiles only."""
    from curvetree.operators import reorder

    monkeypatch.setattr(reorder, "PART_POINTS", 50)
    cloud = spark.range(600).selectExpr("id as pid", "case when id < 400 then 5D else id / 1D end as x", "1D as y", "2D as z")
    index = build_index(cloud, "hilbert", 8, 60)
    assert index.parts == 12 and len(index.tiles) >= 10 and (index.tiles.idx_hi - index.tiles.idx_lo).max() <= 60
    q = spark.createDataFrame([(7, 5.0, 1.0, 2.0), (580, 580.0, 1.0, 2.0)], "cid long, qx double, qy double, qz double")
    for structure in ("ranges", "prune", "pointer"):
        got = tiles.radius_summary(index, q, tiles.radius_tiles(index, q, SPHERE, 6.0, structure))
        costs.assert_same_set(got, relational.summarise(relational.radius_brute(cloud, q, SPHERE, 6.0), q))
    for method in ("batch", "bestfirst"):
        costs.assert_same_set(tiles.knn_tiles(index, q, 405, method=method).select("cid", "rank", "pid"), relational.knn_brute(cloud, q, 405).select("cid", "rank", "pid"))
    far = q.filter("cid = 580")
    text = plan_text(tiles.radius_tiles(index, far, SPHERE, 6.0))
    assert "PartitionFilters" in text and "part" in text.split("PartitionFilters")[1][:200]


def test_saved_index(spark, event, tmp_path):
    index, q = build_index(event, "hilbert", 16, 300), clouds.sample_centres(event, 10)
    save_index(index, str(tmp_path / "ix"), 3)
    again = load_index(spark, str(tmp_path / "ix"))
    costs.assert_same_set(tiles.radius_summary(again, q, tiles.radius_tiles(again, q, SPHERE, 150.0)), tiles.radius_summary(index, q, tiles.radius_tiles(index, q, SPHERE, 150.0)))
    text = plan_text(again.points.filter("idx >= 5 and idx < 9").select("pid"))
    assert "PushedFilters" in text and "GreaterThanOrEqual(idx,5)" in text


def test_plans(spark, event):
    grid, q = fit_grid(event), clouds.sample_centres(event, 20)
    index = build_index(event, "morton", 16, 300)
    for df in (
        relational.radius_gridjoin(event, q, SPHERE, 30.0, grid),
        tiles.radius_tiles(index, q, SPHERE, 100.0),
        tiles.expand_ranges(tiles.merge_ranges(tiles.radius_tiles(index, q, SPHERE, 100.0)), index.points),
        tiles.knn_tiles(index, q, 5),
        tiles.radius_summary(index, q, tiles.radius_tiles(index, q, SPHERE, 400.0)),
        tiles.merge_lists(tiles.radius_tiles(index, q, SPHERE, 400.0, "prune"), q),
        relational.knn_relational(event, clouds.id_centres(event, 50), 5, grid),
    ):
        assert problems(df) == []
    assert "BroadcastNestedLoopJoin" in problems(relational.radius_brute(event, q, SPHERE, 1.0))


def test_rejected_rows(spark):
    nan, inf = float("nan"), float("inf")
    cloud = spark.createDataFrame([(0, 1.0, 1.0, 1.0), (1, nan, 1.0, 1.0), (2, None, 1.0, 1.0), (3, 1.0, inf, 1.0)], POINT)
    good, bad = clouds.reject_invalid(cloud)
    assert [r["pid"] for r in good.collect()] == [0] and bad.count() == 3


def test_random_order_has_the_null_models_skewness():
    rng = np.random.default_rng(0)
    i, j = rng.integers(0, 10**6, (2, 400_000))
    want = locality.null_model(10**6)
    assert abs(locality.np_skewness(np.abs(i - j).astype(float)) - want["g1"]) < 0.01
    assert abs(np.quantile(np.abs(i - j), 0.25) / want["q1"] - 1) < 0.02


def test_curves_raise_skewness_over_a_random_order(spark, sf_dir):
    cloud = clouds.load(spark, sf_dir, "order")
    g = {r["curve"]: r["g1"] for r in locality.recommend_curve(cloud, 20, 0.2).collect()}
    assert g["hilbert"] > g["none"] and g["morton"] > g["none"] and abs(g["none"] - 0.566) < 0.15


def test_published_model_figures():
    assert round(costs.expected_overhead(52, 0, 0.045) * 100, 2) == 7.31
    assert round(costs.expected_overhead(120, 8, 0.045) * 100, 2) in (41.87, 41.88)
    assert round(costs.expected_overhead(128, 4, 0.029) * 100, 2) == 24.1
    assert round(costs.expected_overhead(28, 0, 0.045) * 100, 2) == 3.94
    assert costs.parallel_efficiency({1: 40.0, 40: 40 / 36})[40] == pytest.approx(0.9)
