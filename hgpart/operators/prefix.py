"""Prefix sums and dense numbering without a window over a single partition."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.store import truncate_lineage


def running_sum(df: DataFrame, order: str, value: str, out: str = "running", exclusive: bool = False) -> DataFrame:
    """``df`` with the sum of ``value`` over all rows up to each in ascending ``order`` (a unique column).

    Rows are dealt by ranges of ``order``; the ranges' totals, as few as there are
    tasks, are summed on the driver, and each range adds its own running sum.
    """
    dealt = truncate_lineage(df.repartitionByRange(order).withColumn("_range", F.spark_partition_id()), "ranges")
    totals = dealt.groupBy("_range").agg(F.sum(value).alias("s"), F.min(order).alias("lo")).collect()
    offsets, at = [], 0
    for r in sorted(totals, key=lambda r: r["lo"]):
        offsets.append((r["_range"], int(at)))
        at += r["s"] or 0
    before = df.sparkSession.createDataFrame(offsets, "_range int, _before long")
    frame = Window.partitionBy("_range").orderBy(order).rowsBetween(Window.unboundedPreceding, -1 if exclusive else 0)
    return dealt.join(F.broadcast(before), "_range").withColumn(out, (F.col("_before") + F.coalesce(F.sum(value).over(frame), F.lit(0))).cast("long")).drop("_range", "_before")


def dense_ids(keys: DataFrame, key: str, out: str = "id") -> DataFrame:
    """Distinct values of ``key`` numbered 0, 1, ... in ascending order."""
    return running_sum(keys.select(key).distinct().withColumn("_one", F.lit(1)), key, "_one", out, exclusive=True).drop("_one")
