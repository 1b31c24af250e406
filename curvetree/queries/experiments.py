"""The workloads W1 to W20 on small sets of parameters: what they find and how much they touch, without times.

W6, W7, W18 and W19 are also the queries locality_bins, locality_quartiles, locality_skewness, octree_shallow and
jump_profile; W12 measures times only and runs from the command line.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession

from . import sqltext as s

TYPES = {str: "string", int: "long", float: "double", bool: "boolean"}
_BENCHES: dict[tuple, object] = {}
SAMPLE = 100


def bench(spark: SparkSession, d: str):
    from ..workloads.experiments import Bench

    key = (spark.sparkContext.applicationId, d)
    if key not in _BENCHES:
        _BENCHES[key] = Bench(spark, d, tile_points=2000)
    return _BENCHES[key]


def _table(spark: SparkSession, rows: list[dict], columns: tuple[str, ...]) -> DataFrame:
    """The named columns of a workload's rows: a few rows that are on the driver already."""
    schema = ", ".join(f"{c} {TYPES[type(next(r[c] for r in rows))]}" for c in columns)
    return spark.createDataFrame([tuple(round(r[c], 6) if isinstance(r[c], float) else r[c] for c in columns) for r in rows], schema)


def run(name: str, columns: tuple[str, ...], options: dict, spark: SparkSession, d: str) -> DataFrame:
    from ..workloads.experiments import WORKLOADS

    return _table(spark, WORKLOADS[name](bench(spark, d), **options), columns)


FOUND = ("cloud", "structure", "kernel", "r", "n", "pid_sum")
#: name -> (workload, columns, parameters)
RUNS: dict[str, tuple[str, tuple[str, ...], dict]] = {
    "w1_full_searches": ("W1", (*FOUND, "centres"), {"names": ("event",), "radii": (50.0,)}),
    "w2_random_searches": ("W2", (*FOUND, "centres"), {"n": SAMPLE, "name": "order", "radii": (100.0,)}),
    "w3_five_configurations": ("W3", (*FOUND, "curve"), {"n": SAMPLE, "names": ("event",), "kernels": ("sphere", "square"), "radii": (100.0,)}),
    "w4_own_methods": ("W4", FOUND, {"n": SAMPLE, "names": ("order",), "radii": (50.0, 200.0)}),
    "w5_full_search_table": ("W5", (*FOUND, "bucket", "centres"), {"names": ("event",), "radii": (50.0,), "buckets": (16,)}),
    "w8_all_structures": ("W8", FOUND, {"n": SAMPLE, "names": ("event",), "radii": (100.0,)}),
    "w11_nearest_neighbours": ("W11", ("cloud", "structure", "k", "pairs", "pid_sum"), {"names": ("part",), "sizes": (1, 10, 50), "sets": (None,)}),
    "w13_memory": ("W13", ("cloud", "structure", "nodes", "points", "bytes", "overhead"), {"names": ("order",)}),
    "w14_model_and_measurement": ("W14", ("cloud", "structure", "rho", "measured", "model", "published_model"), {"names": ("order", "part")}),
    "w16_leaf_sizes": ("W16", (*FOUND, "bucket", "nodes", "contained", "leaves", "tested", "bulk"), {"n": SAMPLE, "names": ("event",), "buckets": (16, 128)}),
    "w20_forms_of_results": ("W20", ("cloud", "r", "form", "n", "pid_sum"), {"n": SAMPLE, "names": ("event",), "radii": (200.0,)}),
}
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {n: partial(run, *x) for n, x in RUNS.items()}


def _sums(cloud: str, centres: str, kernel: str, r: float) -> str:
    return f"SELECT '{cloud}' AS cloud, '{kernel}' AS kernel, {r!r}::DOUBLE AS r, count(*) AS n, coalesce(sum(pid), 0)::BIGINT AS pid_sum FROM (WITH p AS ({s.CLOUD[cloud]}), {centres} SELECT p.pid FROM p, q WHERE {s.hit(kernel, r)}) x"


def _found(cloud: str, centres: str, kernels: tuple[str, ...], radii: tuple[float, ...], more: str, values: str, names: str) -> str:
    """Each search's sums beside each arm."""
    rows = " UNION ALL ".join(_sums(cloud, centres, k, r) for k in kernels for r in radii)
    return f"SELECT f.*, {more} FROM ({rows}) f, (VALUES {values}) v({names})"


_SOME, _EACH = s.sampled(SAMPLE), s.by_id(1)
_FOUR = "('pointer'), ('leafscan'), ('prune'), ('ranges')"
_KNN = " UNION ALL ".join(f"SELECT {k}::BIGINT AS k, count(*) AS pairs, sum(pid)::BIGINT AS pid_sum FROM (WITH p AS ({s.CLOUD['part']}), {_EACH}, {s.knn(k)} SELECT pid FROM n) x{k}" for k in (1, 10, 50))
ORACLE = {
    "w1_full_searches": _found("event", _EACH, ("sphere", "circle", "cube", "square"), (50.0,), "structure, (SELECT count(*) FROM events) AS centres", "('ranges')", "structure"),
    "w2_random_searches": _found("order", _SOME, ("sphere", "circle", "cube", "square"), (100.0,), f"structure, least({SAMPLE}, (SELECT count(*) FROM orders))::BIGINT AS centres", "('ranges')", "structure"),
    "w3_five_configurations": _found("event", _SOME, ("sphere", "square"), (100.0,), "structure, curve", "('pointer', 'none'), ('pointer', 'morton'), ('pointer', 'hilbert'), ('leafscan', 'morton'), ('leafscan', 'hilbert')", "structure, curve"),
    "w4_own_methods": _found("order", _SOME, ("sphere",), (50.0, 200.0), "structure", _FOUR, "structure"),
    "w5_full_search_table": _found("event", _EACH, ("sphere",), (50.0,), "structure, 16::BIGINT AS bucket, (SELECT count(*) FROM events) AS centres", _FOUR, "structure"),
    "w8_all_structures": _found("event", _SOME, ("sphere",), (100.0,), "structure", f"{_FOUR}, ('noncomplete'), ('resolution'), ('kd_small'), ('kd_ten'), ('kd_sliding'), ('gridjoin')", "structure"),
    "w11_nearest_neighbours": f"SELECT 'part' AS cloud, structure, k, pairs, pid_sum FROM ({_KNN}) x, (VALUES ('prune'), ('resolution'), ('kd_small'), ('kd_ten'), ('kd_sliding')) v(structure)",
    "w20_forms_of_results": f"SELECT 'event' AS cloud, r, form, n, pid_sum FROM ({_sums('event', _SOME, 'sphere', 200.0)}) x, (VALUES ('ranges'), ('indices'), ('coords')) v(form)",
}
