"""Dense global ranks and running sums by two levels, so that no task sees all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise


def global_rank(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """Adds ``name``: 0, 1, ... in the given order. One range shuffle and a stored table; the counts of its partitions,
    as many rows as there are partitions, are summed and broadcast. ``discard`` of the result deletes the stored table."""
    placed = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", F.monotonically_increasing_id())
    placed = materialise(placed, "ranked")
    part, within = F.shiftright("__m", 33), F.col("__m").bitwiseAND(F.lit((1 << 33) - 1))
    counts = placed.groupBy(part.alias("__p")).count()
    starts = counts.selectExpr("__p", "coalesce(sum(count) over (order by __p rows between unbounded preceding and 1 preceding), 0) as __s")
    out = placed.withColumn("__p", part).join(F.broadcast(starts), "__p").withColumn(name, F.col("__s") + within).drop("__p", "__s", "__m")
    out._scratch = placed._scratch
    return out


def running_start(df: DataFrame, group: F.Column, order: str, amount: str, name: str) -> DataFrame:
    """Adds the sum of ``amount`` over all rows of smaller ``order``. ``group`` must rise with ``order`` and take few values (tens of thousands)."""
    from pyspark.sql import Window

    keyed = df.withColumn("__g", group)
    sums = keyed.groupBy("__g").agg(F.sum(amount).alias("__n"))
    starts = sums.selectExpr("__g", "coalesce(sum(__n) over (order by __g rows between unbounded preceding and 1 preceding), 0) as __s")
    inside = Window.partitionBy("__g").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return keyed.withColumn("__i", F.coalesce(F.sum(amount).over(inside), F.lit(0))).join(F.broadcast(starts), "__g").withColumn(name, F.col("__s") + F.col("__i")).drop("__g", "__i", "__s")
