from __future__ import annotations

from pyspark.sql import functions as F

from curvetree import streaming
from curvetree.functions.curves import encode
from curvetree.functions.grid import fit_grid
from curvetree.functions.kernels import SPHERE
from curvetree.operators import tiles
from curvetree.operators.reorder import build_index
from curvetree.sources import clouds


def _stream(spark, sf_dir, tmp_path):
    """Events as a stream of four files in order of time."""
    cloud = clouds.load(spark, sf_dir, "event")
    times = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("pid"), F.col("ts").cast("timestamp").alias("ts"), "user_id")
    rows = cloud.join(times, "pid").orderBy("ts").coalesce(1).toPandas()
    for i in range(4):
        part = rows.iloc[i * len(rows) // 4 : (i + 1) * len(rows) // 4]
        spark.createDataFrame(part).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    static = spark.read.parquet(str(tmp_path / "in"))
    return static, streaming.read_events(spark, str(tmp_path / "in"), static.schema), fit_grid(cloud)


def _run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return df.sparkSession.table(name)


def test_windowed_octants_match_the_batch(spark, sf_dir, tmp_path):
    static, stream, grid = _stream(spark, sf_dir, tmp_path)
    got = _run(streaming.octant_windows(streaming.encode_stream(stream, grid), 1, grid), "octants", "complete")
    want = encode(static, grid, "morton").groupBy(F.window("ts", "1 day").start.alias("start"), F.shiftright("code", 60).alias("prefix")).count()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_encode_flags_points_outside(spark, sf_dir, tmp_path):
    static, _, grid = _stream(spark, sf_dir, tmp_path)
    moved = streaming.encode_stream(static.withColumn("x", F.col("x") + 1e6), grid)
    assert moved.filter("not outside").count() == 0 and moved.filter("cx < 0 or cx >= 2097152").count() == 0


def test_neighbours_of_each_batch(spark, sf_dir, tmp_path):
    static, stream, _ = _stream(spark, sf_dir, tmp_path)
    cloud = static.select("pid", "x", "y", "z")
    index, found = build_index(cloud, "hilbert", 16, 300), []
    centres = stream.filter("pid % 50 = 0").select(F.col("pid").alias("cid"), *(F.col(a).alias(f"q{a}") for a in "xyz"))
    q = centres.writeStream.foreachBatch(streaming.neighbour_batches(index, 100.0, lambda df, _: found.extend(df.select("cid", "n").collect()))).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    own = clouds.all_centres(cloud.filter("pid % 50 = 0"))
    want = tiles.radius_summary(index, own, tiles.radius_tiles(index, own, SPHERE, 100.0)).select("cid", "n")
    assert sorted(map(tuple, found)) == sorted(map(tuple, want.collect()))
