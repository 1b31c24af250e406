"""Registered queries against SQL, on the smallest tables."""

from __future__ import annotations

import pytest

from curvetree import queries
from tests.oracle import assert_same, connect

# every kernel and structure is covered by the driver's own run; tests take one of each kind
SLOW = {n for n in queries.QUERIES if n.startswith(("radius_circle", "radius_cube", "radius_square", "radius_kdtree_small", "node_ratio"))}


@pytest.fixture(scope="module")
def con(sf_dir):
    return connect(sf_dir)


@pytest.mark.parametrize("name", sorted(set(queries.ORACLE) - SLOW))
def test_same_as_sql(name, spark, sf_dir, con):
    assert_same(queries.QUERIES[name](spark, sf_dir), con, queries.ORACLE[name])


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.ORACLE)))
def test_others_give_rows(name, spark, sf_dir):
    assert queries.QUERIES[name](spark, sf_dir).count() > 0


def test_every_oracle_has_a_query():
    assert set(queries.ORACLE) <= set(queries.QUERIES)
