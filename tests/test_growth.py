"""Work that must not grow with the shape of a cloud or the size of its groups."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from curvetree.functions.grid import fit_grid
from curvetree.operators import costs, relational, tiles
from curvetree.operators.reorder import build_index
from curvetree.queries import searches
from curvetree.sources import clouds


@pytest.fixture(scope="module")
def long_cloud(spark):
    """Points along one axis 100,000 times as long as the others."""
    at = spark.range(4000).select(F.col("id").alias("pid"), (F.col("id") * 25000.0).alias("x"), (F.col("id") * 7919 % 1000 / 1.0).alias("y"), (F.col("id") * 104729 % 997 / 1.0).alias("z"))
    return at.localCheckpoint()


def test_centres_visit_few_tiles_of_a_long_cloud(spark, long_cloud, monkeypatch):
    routed = []

    def spy(df, name, **options):
        out = kept(df, name, **options)
        if name == "routed":
            routed.append(out.count())
        return out

    kept = tiles.materialise
    monkeypatch.setattr(tiles, "materialise", spy)
    monkeypatch.setattr(searches.clouds, "load", lambda *_: long_cloud)
    got = searches.knn("prune", "batch", spark, "long")
    q = clouds.id_centres(long_cloud)
    costs.assert_same_set(got, relational.knn_brute(long_cloud, q, searches.K).select("cid", "rank", "pid"))
    index = build_index(long_cloud, "hilbert", 16, 50, fit_grid(long_cloud, box="cubic"))
    got = tiles.knn_tiles(index, q, 5).select("cid", "rank", "pid")
    costs.assert_same_set(got, relational.knn_brute(long_cloud, q, 5).select("cid", "rank", "pid"))
    assert routed[-1] <= 2 * 40  # of 40 centres, each its own tile and rarely the next; all 80 tiles or more once


def test_ball_cover_joins_few_cells_of_a_long_cloud(spark, long_cloud, monkeypatch):
    seen = []
    top = relational.top_k

    def spy(pairs, k):
        seen.append(pairs.count())
        return top(pairs, k)

    monkeypatch.setattr(relational, "top_k", spy)
    q = clouds.id_centres(long_cloud)
    got = relational.knn_relational(long_cloud, q, 5, fit_grid(long_cloud)).select("cid", "rank", "pid")
    monkeypatch.undo()
    costs.assert_same_set(got, relational.knn_brute(long_cloud, q, 5).select("cid", "rank", "pid"))
    assert seen[0] <= 40 * 100


def test_lateral_ranks_are_ordered(spark, sf_dir):
    from curvetree.plans.checks import plan_text
    from curvetree.queries import relational_ops

    windows = [line for line in plan_text(relational_ops.QUERIES["op_join_lateral"](spark, sf_dir)).splitlines() if "windowspecdefinition" in line]
    assert windows and all("o_totalprice" in line for line in windows)


@pytest.mark.parametrize("name, table", [("curve_continuity", "orders"), ("overhead_model", "events")])
def test_reads_a_table(spark, sf_dir, name, table):
    from curvetree.queries import structure

    assert any(f"/{table}.parquet" in f for f in read_files(spark, structure.QUERIES[name], sf_dir))


def read_files(spark, query, sf_dir) -> set[str]:
    """The files that Spark's scans are asked for while a query is built and run."""
    seen, load = set(), type(spark.read).parquet

    def spy(self, *paths, **options):
        seen.update(paths)
        return load(self, *paths, **options)

    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(type(spark.read), "parquet", spy)
        query(spark, sf_dir).collect()
    return seen


def test_counts_make_no_pairs(spark, sf_dir, monkeypatch):
    """Every kernel against brute force, with coincident points and one without a place; no join lists pairs."""
    import numpy as np

    from curvetree.functions.kernels import KERNELS
    from curvetree.operators import features

    rng = np.random.default_rng(5)
    xyz = rng.integers(0, 60, (400, 3)) * [10.0, 5.0, 2.5]
    rows = [(i, *p) for i, p in enumerate(xyz.tolist())] + [(400 + i, *xyz[i % 7].tolist()) for i in range(60)] + [(900, float("nan"), 0.0, 0.0)]
    cloud = spark.createDataFrame(rows, "pid long, x double, y double, z double")
    monkeypatch.setattr(features, "radius_gridjoin", None)
    at = {r[0]: r[1:] for r in rows}
    for name, kernel in KERNELS.items():
        got = {r["cid"]: r["n"] for r in features.density(cloud, fit_grid(cloud.filter("pid < 900")), kernel, 50.0).collect()}
        p = np.array([v for k, v in at.items() if k < 900])
        want = {k: int(kernel.np_hits(p, np.array([at[k]]), np.full(len(p), 50.0)).sum()) if k < 900 else 0 for k in at}
        assert got == want, name


@pytest.mark.parametrize("structure", ["prune", "pointer", "kd_sliding", "resolution"])
def test_best_first_moves_all_queues_at_once(structure, monkeypatch):
    """The same as two phases and as one centre's queue, with ties, coincident points and bounds; no centre is searched alone."""
    import numpy as np

    from curvetree.functions.curves import np_encode
    from curvetree.functions.grid import GridSpec
    from curvetree.operators.local import Walk, build_local

    rng = np.random.default_rng(3)
    xyz = np.concatenate((rng.integers(0, 12, (700, 3)) * 5.0, np.full((90, 3), 30.0)))
    pid, grid = rng.permutation(len(xyz)), GridSpec((0.0, 0.0, 0.0), (55.0, 55.0, 55.0))
    code = np_encode(grid.np_cells(xyz), "hilbert", 21)
    order = np.lexsort((pid, code))
    xyz, pid, code = xyz[order], pid[order], code[order]
    tree = build_local(structure, xyz, code, grid, "hilbert", 16, (0, 0), (np.zeros(3), np.full(3, 55.0)), 9.0)
    bound = np.where(pid % 3, np.inf, 100.0)
    one = [(i, d, item) for i in range(len(pid)) for d, _, item in tree.knn(xyz[i], 20, pid, pid[i], bound[i])]
    monkeypatch.setattr(Walk, "knn", None)
    for search in (tree.knn_bestfirst, tree.knn_batch):
        who, d2, item = search(xyz, 20, pid, pid, bound.copy())
        by_centre = np.argsort(who, kind="stable")
        assert [*zip(who[by_centre].tolist(), d2[by_centre].tolist(), item[by_centre].tolist(), strict=True)] == one
    lists = {}
    for i, d, _ in one:
        lists.setdefault(i, []).append(d)
    assert tree.kth_batch(xyz, 20, bound).tolist() == [max(lists[i]) if len(lists[i]) == 20 else bound[i] for i in range(len(pid))]


def test_gaps_are_counted_without_stored_lists(spark, long_cloud, monkeypatch):
    """The same histograms as from pairs, over tiles that centres share; no list of neighbours is written."""
    from curvetree.operators import locality

    stored, kept = [], tiles.materialise

    def spy(df, name, **options):
        stored.append(name)
        assert not any(t.startswith("array") for _, t in df.dtypes)
        return kept(df, name, **options)

    index, grid, q = build_index(long_cloud, "hilbert", 16, 300, fit_grid(long_cloud, box="cubic")), fit_grid(long_cloud), clouds.all_centres(long_cloud)
    pairs = locality.list_gaps(locality.neighbour_ranks(index, long_cloud, q, 9, grid)).localCheckpoint()
    for module in (tiles, locality):
        monkeypatch.setattr(module, "materialise", spy)
    counted = locality.neighbour_gaps(index, long_cloud, q, 9, grid).localCheckpoint()
    assert stored
    costs.assert_same_set(locality.histogram(counted), locality.histogram(pairs))
    costs.assert_same_set(locality.histogram(counted, False), locality.histogram(pairs, False))
    want = locality.gap_multiplicity(pairs).groupBy("curve", "d", "n").agg(F.count("*").alias("h"))
    costs.assert_same_set(counted, want)


def test_nodes_are_counted_without_the_cloud_on_the_driver(spark, monkeypatch):
    """As many nodes and bytes as the structures themselves have, with coincident points and medians among equals."""
    import numpy as np

    from curvetree.operators.sizes import bytes_held, count_nodes
    from curvetree.workloads import experiments

    rng = np.random.default_rng(11)
    xyz = np.concatenate((rng.integers(0, 40, (1500, 3)) * [9.0, 5.0, 2.3], np.full((300, 3), 41.4)))
    cloud = spark.createDataFrame([(i, *p) for i, p in enumerate(xyz.tolist())], "pid long, x double, y double, z double").localCheckpoint()
    b = experiments.Bench(spark, "made")
    monkeypatch.setattr(clouds, "load", lambda *_: cloud)
    monkeypatch.setattr(experiments.clouds, "load", lambda *_: cloud)
    want = {label: experiments.local_structure(b, "made", structure, "hilbert")[0] for label, structure in experiments.MADE.items()}
    monkeypatch.setattr(experiments, "local_structure", None)
    for label, structure in experiments.MADE.items():
        assert count_nodes(cloud, fit_grid(cloud), structure, branch=500) == len(want[label].lo), label
        assert bytes_held(structure, len(want[label].lo), len(xyz)) == want[label].node_bytes()
    rows = experiments.w13(experiments.Bench(spark, "made"), ("made",))
    assert {r["structure"]: (r["nodes"], r["bytes"]) for r in rows if "without" not in r["structure"]} == {k: (len(t.lo), t.node_bytes()) for k, t in want.items()}


def test_centres_of_one_tile_are_searched_once(spark, long_cloud, monkeypatch):
    """A centre whose neighbours all lie in its tile is not routed again; what was stored on the way is deleted."""
    import os

    from curvetree.operators import locality, reorder
    from curvetree.plans import ranks

    routed, stored, kept = [], [], tiles.materialise

    def spy(df, name, **options):
        out = kept(df, name, **options)
        stored.append((name, out._scratch.removeprefix("file://")))
        if name == "routed":
            routed.append(out.select("cid").distinct().count())
        return out

    for module in (tiles, locality, reorder, ranks):
        monkeypatch.setattr(module, "materialise", spy)
    index, q = build_index(long_cloud, "hilbert", 16, 300, fit_grid(long_cloud, box="cubic")), clouds.all_centres(long_cloud)
    counted = locality.neighbour_gaps(index, long_cloud, q, 9, fit_grid(long_cloud))
    assert counted.groupBy("curve").agg(F.sum(F.col("n") * F.col("h")).alias("all")).filter("all = 4000 * 9").count() == 3
    assert 0 < routed[-1] < 1000
    left = {name for name, path in stored if os.path.exists(path)}
    assert "gaps" in left and "points" in left and not left & {"ranked", "ranked-points"}


@pytest.mark.parametrize("structure", ["prune", "pointer", "kd_ten"])
def test_blocks_of_centres_share_their_rows(monkeypatch, structure):
    """Nearest neighbours of close centres by full matrices, of scattered ones singly: both as brute force has them, ties too."""
    import numpy as np

    from curvetree.functions.curves import np_encode
    from curvetree.functions.grid import GridSpec
    from curvetree.operators import local

    rng = np.random.default_rng(2)
    for xyz in (rng.integers(0, 12, (3000, 3)) * [7.0, 1.0, 3.0] + 1e6, np.concatenate((rng.random((2500, 3)), np.full((500, 3), 0.3)))):
        low = xyz.min(axis=0)
        grid, pid = GridSpec(tuple(low), (float((xyz - low).max()),) * 3, box="cubic"), rng.permutation(3000)
        code = np_encode(grid.np_cells(xyz), "hilbert", grid.levels)
        order = np.lexsort((pid, code))
        xyz, pid, code = xyz[order], pid[order], code[order]
        tree = local.build_local(structure, xyz, code, grid, "hilbert", 32, (0, 0), (low, low + grid.ext[0]))
        tested, single = [], local.np_d2
        monkeypatch.setattr(local, "np_d2", lambda p, c, *a: tested.append(len(p)) or single(p, c, *a))  # noqa: B023
        for who, reach, most in ((np.arange(3000), np.inf, 4096), (np.arange(3000), grid.ext[0] ** 2 / 50, 4096), (rng.permutation(3000)[:300], np.inf, 100)):
            monkeypatch.setattr(local, "BLOCK_ROWS", most)
            tested.clear()
            c, d, item = tree.knn_batch(xyz[who], 20, pid, pid[who], np.full(len(who), reach))
            assert bool(tested) == (most == 100)  # no pair of a centre and a row is gathered where blocks serve
            got = {(a, b) for a, b in zip(c.tolist(), item.tolist(), strict=True)}
            for i, w in enumerate(who.tolist()):
                far = single(xyz, xyz[[w]])
                near = np.lexsort((pid, np.arange(3000) != w, far))[:20]
                near = near[far[near] <= reach]
                assert {(i, p) for p in pid[near].tolist()} <= got
                got -= {(i, p) for p in pid[near].tolist()}
            assert not got
        monkeypatch.setattr(local, "np_d2", single)


def test_ranks_of_gaps_need_no_join_and_grids_one_fit(spark, sf_dir, monkeypatch):
    from curvetree.operators import locality

    fitted, fit, joined, join = [], searches.fit_grid, [], type(spark.range(1)).join
    monkeypatch.setattr(searches, "fit_grid", lambda *a, **o: fitted.append(a) or fit(*a, **o))
    monkeypatch.setattr(searches, "_GRIDS", {})
    monkeypatch.setattr(searches, "_INDEXES", {})
    index = searches.index_of(spark, sf_dir, "part", bucket=32, box="cubic")
    searches.QUERIES["locality_hist_none"](spark, sf_dir).count()
    searches.QUERIES["locality_invariants"](spark, sf_dir).count()
    assert len(fitted) == 1
    monkeypatch.setattr(type(index.points), "join", lambda a, b, on=None, *more: joined.append(on) or join(a, b, on, *more))
    locality.neighbour_gaps(index, index.points, clouds.all_centres(index.points), 5, searches.grid_of(spark, sf_dir, "part"))
    assert "pid" not in joined
