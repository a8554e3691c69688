"""Joins by range and by time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``points`` with the half-open ranges they lie in.  Ranges are dealt to the buckets of ``width``
    that they touch, so it is an equi-join; wider ranges touch more buckets, and all matches are kept."""
    bucket = lambda c: F.floor(c / F.lit(width)).cast("long")
    a = points.withColumn("__b", bucket(F.col(point)))
    b = ranges.where(F.col(high) > F.col(low)).withColumn("__b", F.explode(F.sequence(bucket(F.col(low)), bucket(F.col(high)))))
    return a.join(b, "__b").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("__b")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Each left row with ``value`` of the newest right row of its key at or before its time (ties: the greatest
    value; none: null).  One shuffle by key: the sides are stacked and the last right row is carried along."""
    columns = [c for c in left.columns if c not in (key, ts)]
    a = left.select(key, ts, F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias(value), F.struct(*columns).alias("__row"))
    b = right.select(key, ts, F.lit(0).alias("__side"), value, F.lit(None).cast(a.schema["__row"].dataType).alias("__row"))
    w = Window.partitionBy(key).orderBy(ts, "__side", value).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("__value", F.last(value, ignorenulls=True).over(w)).where("__side = 1")
    return both.select(key, ts, "__row.*", F.col("__value").alias(value))


def sliding_distinct(events: DataFrame, ts: str, value: str, width: str, slide: str, error: float = 0.05) -> DataFrame:
    """The approximate baseline: distinct values in each sliding window by a sketch of given relative error, with
    nothing kept from window to window: (start, distinct)."""
    windows = events.groupBy(F.window(ts, width, slide)["start"].alias("start"))
    return windows.agg(F.approx_count_distinct(value, error).alias("distinct"))
