from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvetree.functions import curves as c
from curvetree.functions.grid import GridSpec, fit_grid, quantise


def test_worked_example():
    assert c.np_morton(np.array([[3, 7, 2]]))[0] == 190


def test_orientations_close_on_twelve_states():
    digit, following, _ = c.orientation_table()
    assert digit.shape == (12, 8) and following.max() == 11
    assert all(sorted(row) == [*range(8)] for row in digit.tolist())


@pytest.mark.parametrize("level", [1, 2, 3, 4])
def test_curves_are_recursive_bijections(level):
    for curve in ("morton", "hilbert"):
        codes = c.np_encode(c.all_cells(level), curve, level)
        assert sorted(codes.tolist()) == [*range(8**level)]
        assert (c.np_decode(codes, curve, level) == c.all_cells(level)).all()
        assert c.check_recursive(curve, level)
    assert c.check_continuous("hilbert", level)
    assert level < 2 or not c.check_continuous("morton", level)


def test_full_depth_round_trip():
    cells = np.random.default_rng(1).integers(0, 1 << 21, (500, 3))
    cells[0], cells[1] = 0, (1 << 21) - 1
    for curve in ("morton", "hilbert"):
        codes = c.np_encode(cells, curve, 21)
        assert (codes >= 0).all() and (c.np_decode(codes, curve, 21) == cells).all()


def test_two_dimensional_curves():
    cells = np.array([(x, y) for x in range(8) for y in range(8)])
    for curve in ("morton", "hilbert"):
        codes = c.encode2(curve, cells, 3)
        assert sorted(codes.tolist()) == [*range(64)]
    path = cells[np.argsort(c.encode2("hilbert", cells, 3))]
    assert (np.abs(np.diff(path, axis=0)).sum(axis=1) == 1).all()


def test_forms_agree(spark):
    rows = np.random.default_rng(2).integers(0, 1 << 21, (200, 3)).tolist()
    df = spark.createDataFrame(rows, "cx int, cy int, cz int")
    xyz = [F.col(k) for k in ("cx", "cy", "cz")]
    got = df.select(c.morton_encode(*xyz), c.morton_encode(*xyz, method="table"), c.hilbert_encode(*xyz, 21), c.hilbert_encode(*xyz, 21, "native")).collect()
    cells = np.array(rows)
    assert [r[0] for r in got] == [r[1] for r in got] == c.np_morton(cells).tolist()
    assert [r[2] for r in got] == [r[3] for r in got] == c.np_hilbert(cells, 21).tolist()


def test_grid_edges(spark):
    corner = spark.createDataFrame([(0, 0.0, 0.0, 5.0), (1, 1.0, 2.0, 5.0)], "pid long, x double, y double, z double")
    grid = fit_grid(corner)
    assert [tuple(r)[4:] for r in quantise(corner, grid).orderBy("pid").collect()] == [(0, 0, 0), ((1 << 21) - 1, (1 << 21) - 1, 0)]
    assert fit_grid(corner, box="cubic").ext == (2.0, 2.0, 2.0)
    empty = fit_grid(corner.filter("pid < 0"))
    assert empty == GridSpec((0.0, 0.0, 0.0), (0.0, 0.0, 0.0))
    with pytest.raises(ValueError):
        fit_grid(corner, 22)
