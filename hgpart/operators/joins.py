"""Joins that Spark has no name for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """``left(by, on, ...)`` with the ``value`` of the latest ``right(by, on, value)`` at or before it; ties on the right go to the largest value.

    One shuffle by key: both sides are stacked and the last value seen is carried on.
    """
    names = [c for c in left.columns if c not in (by, on)]
    r = right.groupBy(by, on).agg(F.max(value).alias("_value"))
    stacked = left.select(by, on, F.struct(*names).alias("_row"), F.lit(None).cast(r.schema["_value"].dataType).alias("_value"), F.lit(1).alias("_side")).unionByName(
        r.select(by, on, F.lit(None).cast(left.select(F.struct(*names).alias("x")).schema["x"].dataType).alias("_row"), "_value", F.lit(0).alias("_side"))
    )
    w = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return stacked.withColumn(value, F.last("_value", ignorenulls=True).over(w)).filter("_side = 1").select(by, on, *[F.col(f"_row.{c}").alias(c) for c in names], value)


def range_bucketed(points: DataFrame, intervals: DataFrame, at: str, start: str, end: str, width: int) -> DataFrame:
    """Pairs with start <= at < end, joined on buckets of ``width`` that an interval is spread over, so that the join is an equi-join."""
    p = points.withColumn("_bucket", F.floor(F.col(at) / width))
    i = intervals.filter(F.col(start) < F.col(end)).withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor((F.col(end) - 1) / width))))
    return p.join(i, "_bucket").filter((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_bucket")


def salted(left: DataFrame, right: DataFrame, on: str, salts: int = 16) -> DataFrame:
    """Inner equi-join with a hot key on the left: its rows are dealt over ``salts`` and the right side is repeated as often."""
    row = F.xxhash64(*[c for c in left.columns])
    a = left.withColumn("_salt", F.pmod(row, F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.array(*[F.lit(i) for i in range(salts)])))
    return a.join(b, [on, "_salt"]).drop("_salt")


def overlapping(a: DataFrame, b: DataFrame, ia: tuple[str, str], ib: tuple[str, str], width: int) -> DataFrame:
    """Pairs of rows whose half-open intervals share a point. Intervals are listed under each bucket of ``width`` that they touch; a pair is formed in the first bucket both touch."""
    buckets = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.greatest(F.col(hi), F.col(lo) + 1) - 1) / width)))
    x, y = a.withColumn("_bucket", buckets(*ia)), b.withColumn("_bucket", buckets(*ib))
    first = F.greatest(F.floor(F.col(ia[0]) / width), F.floor(F.col(ib[0]) / width))
    return x.join(y, "_bucket").filter((F.col(ia[0]) < F.col(ib[1])) & (F.col(ib[0]) < F.col(ia[1])) & (F.col("_bucket") == first)).drop("_bucket")
