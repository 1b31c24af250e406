"""Measures without SQL against brute force: the simulated cache, local shapes, memory and its model, stream operators."""

from __future__ import annotations

import subprocess
import sys

import numpy as np
from pyspark.sql import functions as F

from curvetree.functions.curves import encode
from curvetree.functions.grid import fit_grid
from curvetree.operators import costs, locality
from curvetree.operators.reorder import load_index
from curvetree.queries import searches
from curvetree.sources import clouds
from curvetree.streaming import points as stream
from curvetree.workloads import experiments


def test_simulated_cache(spark, sf_dir):
    gaps = searches._gaps(spark, sf_dir, "embed", k=5)
    got = {r["curve"]: r["misses_per_centre"] for r in locality.lru_misses(gaps, 8, 2).collect()}
    rows = sorted((r["curve"], r["i"], r["j"]) for r in gaps.collect())
    for curve in ("none", "morton", "hilbert"):
        held, misses, own = [], 0, [(i, j) for c, i, j in rows if c == curve]
        for _, j in own:
            if j // 2 not in held:
                misses += 1
            else:
                held.remove(j // 2)
            held = [*held, j // 2][-8:]
        assert abs(got[curve] - misses / len({i for i, _ in own})) < 1e-9


def test_local_shapes(spark, sf_dir):
    p = clouds.load(spark, sf_dir, "order")
    xyz = {r["pid"]: np.array([r["x"], r["y"], r["z"]]) for r in p.collect()}
    every = np.array([*xyz.values()])
    for r in searches.shapes(spark, sf_dir).collect():
        near = every[((every - xyz[r["cid"]]) ** 2).sum(axis=1) < 100.0**2]
        values, vectors = np.linalg.eigh(np.cov(near.T, bias=True)) if len(near) > 1 else (np.zeros(3), None)
        top = values[2] if values[2] > 0 else 1.0
        assert abs(r["linearity"] - (values[2] - values[1]) / top) < 1e-6 and abs(r["planarity"] - (values[1] - values[0]) / top) < 1e-6 and abs(r["sphericity"] - values[0] / top) < 1e-6
        if vectors is not None and values[1] - values[0] > 1e-3 * top:
            assert abs(abs(np.dot(vectors[:, 0], [r["nx"], r["ny"], r["nz"]])) - 1) < 1e-6


def test_memory_and_its_model(spark, sf_dir):
    """The model predicts the arrays' bytes, and the linear octree is the smallest of the complete ones."""
    b = experiments.Bench(spark, sf_dir)
    for r in experiments.w14(b, ("order", "event")):
        assert abs(r["measured"] / r["model"] - 1) < 0.05, r
    size = {r["structure"]: r["bytes"] for r in experiments.w13(b, ("order",))}
    assert size["linear octree without boxes"] < size["linear octree"] < size["pointer octree"] < size["kd-tree, leaf 10"] < size["kd-tree, leaf 1"]


def test_choice_by_sample(spark, sf_dir):
    for r in experiments.w17(experiments.Bench(spark, sf_dir), ("part",), (0.5,)):
        assert r["choice"] == r["full_choice"] and r["error"] < 0.5


def test_reorder_program(spark, sf_dir, tmp_path):
    clouds.load(spark, sf_dir, "part").write.parquet(str(tmp_path / "cloud"))
    subprocess.run([sys.executable, "-m", "curvetree.reorder", "--in", str(tmp_path / "cloud"), "--out", str(tmp_path / "index")], check=True, timeout=240, capture_output=True)
    index = load_index(spark, str(tmp_path / "index"))
    assert index.points.count() == clouds.load(spark, sf_dir, "part").count() == index.points.agg(F.max("idx")).first()[0] + 1
    codes = [r["code"] for r in index.points.orderBy("idx").collect()]
    assert codes == sorted(codes)


def _coded(spark, sf_dir, tmp_path):
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("pid"), "user_id", F.col("ts").cast("timestamp").alias("ts"))
    cloud = clouds.load(spark, sf_dir, "event")
    grid = fit_grid(cloud)
    coded = encode(cloud.join(rows, "pid"), grid, "morton").select("pid", "user_id", "ts", "code")
    coded.repartition(2).write.parquet(str(tmp_path / "events"))
    return coded, grid, str(tmp_path / "events")


def _run(df, name: str, mode: str):
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination(180)
    return df.sparkSession.table(name)


def test_sessions(spark, sf_dir, tmp_path):
    coded, _, path = _coded(spark, sf_dir, tmp_path)
    got = _run(stream.session_counts(stream.read_events(spark, path, coded.schema, 10)), "curvetree_sessions", "complete")
    want = coded.groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")
    costs.assert_same_set(got, want)


def test_overfull(spark, sf_dir, tmp_path):
    coded, grid, path = _coded(spark, sf_dir, tmp_path)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got = _run(stream.overfull_octants(stream.read_events(spark, path, coded.schema, 10), 2, grid, 20), "curvetree_overfull", "update")
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    want = coded.groupBy(F.shiftright("code", 3 * (grid.levels - 2)).alias("prefix")).count().filter("count > 20").select("prefix")
    costs.assert_same_set(got.select("prefix"), want)


def test_close_events(spark, sf_dir, tmp_path):
    coded, grid, path = _coded(spark, sf_dir, tmp_path)
    side = lambda: stream.read_events(spark, path, coded.schema, 10).select(F.col("pid").alias("id"), "ts", "code")
    got = _run(stream.close_events(side(), side(), grid, 3), "curvetree_close", "append").select("a", "b")
    prefix = F.shiftright("code", 3 * (grid.levels - 3))
    x = coded.select(F.col("pid").alias("a"), F.col("ts").alias("ta"), prefix.alias("pa"))
    y = coded.select(F.col("pid").alias("b"), F.col("ts").alias("tb"), prefix.alias("pb"))
    want = x.join(y, (F.col("pa") == F.col("pb")) & (F.abs(F.unix_micros("ta") - F.unix_micros("tb")) <= 3_600_000_000)).select("a", "b")
    costs.assert_same_set(got, want)
