"""Sessions and tables that outlive a plan."""

from __future__ import annotations

import tempfile
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The most rows that any operator here broadcasts or brings to the driver; beyond it, the shuffled way is taken or an error raised.
SMALL_ROWS = 1_000_000


def local_session(cores: int = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session for tests and benches on one machine."""
    conf = {
        "spark.sql.shuffle.partitions": partitions,
        "spark.driver.memory": memory,
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
        "spark.sql.session.timeZone": "UTC",
    }
    builder = SparkSession.builder.master(f"local[{cores}]").appName("curvetree")
    for k, v in conf.items():
        builder = builder.config(k, v)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def scratch_dir(spark: SparkSession) -> str:
    """The folder all executors share. Where the session names none, a temporary one is set in local mode, as in tests; on
    a cluster that is an error, since executors would not see one another's files."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        where = "file://" + tempfile.mkdtemp(prefix="curvetree-")
        spark.sparkContext.setCheckpointDir(where)
    return where


def materialise(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage and survives lost executors. ``by``: a folder for each value."""
    path = f"{scratch_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def discard(df: DataFrame) -> None:
    """Delete the files of a table that ``materialise`` made, once nothing that is still to run reads it."""
    path = getattr(df, "_scratch", None)
    if path:
        jvm = df.sparkSession.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def small(df: DataFrame, limit: int = SMALL_ROWS) -> DataFrame:
    """A broadcast of ``df`` if it holds at most ``limit`` rows, else ``df`` as it is, to be shuffled. Counts it first: give it stored tables."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


def collect_small(df: DataFrame, limit: int = SMALL_ROWS) -> list:
    """All rows on the driver; raises beyond ``limit`` instead of filling its memory."""
    rows = df.limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"more than {limit} rows where a small table is needed")
    return rows


def small_frame(df: DataFrame, limit: int = SMALL_ROWS) -> pd.DataFrame:
    """All rows on the driver as a pandas frame of columns, not of row objects; raises beyond ``limit``."""
    rows = df.limit(limit + 1).toPandas()
    if len(rows) > limit:
        raise ValueError(f"more than {limit} rows where a small table is needed")
    return rows
