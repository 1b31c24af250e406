"""Local structures against brute force on awkward clouds."""

from __future__ import annotations

import numpy as np
import pytest

from curvetree.functions.curves import np_encode
from curvetree.functions.grid import GridSpec
from curvetree.functions.kernels import KERNELS, np_d2
from curvetree.operators.local import STRUCTURES, build_local, coalesce

RNG = np.random.default_rng(5)
CLOUDS = {
    "random": RNG.uniform(-50, 50, (400, 3)),
    "same": np.ones((100, 3)),
    "line": np.stack([np.linspace(0, 9, 60), np.zeros(60), np.zeros(60)], 1),
    "lattice": np.array([(x, y, z) for x in range(6) for y in range(6) for z in range(6)], float),
    "single": np.array([[3.0, 4.0, 5.0]]),
    "skewed": np.concatenate([RNG.normal(0, 0.01, (200, 3)), RNG.uniform(-100, 100, (50, 3))]),
}


def build(structure, xyz, curve="hilbert", bucket=8, tight=False):
    lo, hi = xyz.min(axis=0), xyz.max(axis=0)
    grid = GridSpec(tuple(lo), tuple(hi - lo))
    codes = np_encode(grid.np_cells(xyz), curve, 21)
    order = np.argsort(codes, kind="stable")
    return build_local(structure, xyz[order], codes[order], grid, curve, bucket, (0, 0), (lo, hi), max((hi - lo).max() / 8, 0.1), tight), xyz[order]


@pytest.mark.parametrize("cloud", CLOUDS)
@pytest.mark.parametrize("structure", STRUCTURES)
def test_radius_is_exact(cloud, structure):
    tree, xyz = build(structure, CLOUDS[cloud])
    q = np.concatenate([xyz[:20], xyz[:3] + 1000, xyz.mean(axis=0, keepdims=True)])
    for kernel in KERNELS.values():
        for r in (0.0, 1.0, 2.0, 30.0, 1e6):
            who, lo, hi, work = tree.radius(kernel, q, np.full(len(q), r), structure)
            got = {(int(w), i) for w, a, b in zip(who, lo, hi, strict=True) for i in range(a, b)}
            want = {(c, int(i)) for c in range(len(q)) for i in np.flatnonzero(kernel.np_hits(xyz, np.repeat(q[c : c + 1], len(xyz), 0), np.full(len(xyz), r)))}
            assert got == want
            assert work[:, 5].sum() == len(who)


@pytest.mark.parametrize("cloud", CLOUDS)
@pytest.mark.parametrize("structure", STRUCTURES)
def test_nearest_is_exact(cloud, structure):
    tree, xyz = build(structure, CLOUDS[cloud])
    key = np.arange(len(xyz))
    for c in (0, len(xyz) - 1):
        for k in (1, 7, len(xyz), len(xyz) + 1):
            got = tree.knn(xyz[c], k, key, c)
            d = np_d2(xyz, np.repeat(xyz[c : c + 1], len(xyz), 0))
            want = sorted((float(d[i]), int(i != c), i) for i in range(len(xyz)))[:k]
            assert got == want


def test_range_edge_is_strict():
    xyz = np.array([[0.0, 0, 0], [3.0, 0, 0], [3.0, 4.0, 0]])
    tree, pts = build("ranges", xyz)
    who, lo, hi, _ = tree.radius(KERNELS["sphere"], np.array([[0.0, 0, 0]]), np.array([3.0]))
    assert sum(hi - lo) == 1


def test_containment_saves_tests():
    xyz = RNG.uniform(0, 100, (3000, 3))
    prune, pts = build("prune", xyz, bucket=16)
    q, r = pts[:50], np.full(50, 40.0)
    a = prune.radius(KERNELS["sphere"], q, r, "leafscan")[3].sum(axis=0)
    b = prune.radius(KERNELS["sphere"], q, r, "prune")[3].sum(axis=0)
    literal = prune.radius(KERNELS["sphere"], q, r, "prune", contain_leaves=False)
    assert a[1] == 0 and b[1] > 0 and b[3] < a[3] and b[3] + b[4] <= a[3] and b[0] < a[0]
    assert (literal[1] == prune.radius(KERNELS["sphere"], q, r)[1]).all()
    tight, _ = build("prune", xyz, bucket=16, tight=True)
    assert (tight.radius(KERNELS["sphere"], q, r)[1] == literal[1]).all()


def test_monotone_and_nested_kernels():
    tree, pts = build("ranges", CLOUDS["random"])
    q = pts[:30]
    n = lambda k, r: np.bincount(*(lambda w, lo, hi, _: (w, hi - lo))(*tree.radius(KERNELS[k], q, np.full(30, r))), minlength=30)
    assert (n("sphere", 10.0) <= n("sphere", 20.0)).all()
    assert (n("sphere", 20.0) <= n("circle", 20.0)).all() and (n("sphere", 20.0) <= n("cube", 20.0)).all()
    assert (n("cube", 20.0) <= n("square", 20.0)).all() and (n("circle", 20.0) <= n("square", 20.0)).all()


def test_coalesced_ranges_are_disjoint():
    who, lo, hi = coalesce(np.array([0, 0, 1, 0]), np.array([5, 0, 0, 3]), np.array([7, 3, 2, 5]))
    assert [*zip(who, lo, hi, strict=True)] == [(0, 0, 7), (1, 0, 2)]


def test_memory_order():
    xyz = RNG.uniform(0, 100, (4000, 3))
    size = {s: build(s, xyz, bucket=128)[0].node_bytes() for s in ("ranges", "pointer", "noncomplete", "kd_small")}
    assert size["ranges"] < size["noncomplete"] < size["pointer"] < size["kd_small"]
