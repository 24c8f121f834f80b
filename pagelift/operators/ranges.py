"""Joins that Spark has no operator for, as compositions of ones it has."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(spans: DataFrame, points: DataFrame, low: str, high: str, at: str, width: int) -> DataFrame:
    """Rows of points with low <= at <= high of spans, both bounds timestamps.

    Time is cut into buckets of `width` seconds: a point lies in one, a span in each that it touches.  The join is then on
    equal buckets, with the exact condition on top, so neither side is compared with all of the other.
    """
    bucket = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / width)
    a = spans.withColumn("__bucket", F.explode(F.sequence(bucket(low), bucket(high))))
    b = points.withColumn("__bucket", bucket(at))
    return a.join(b, "__bucket").where(F.col(at).between(F.col(low), F.col(high))).drop("__bucket")


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, take: list[str], slice_by: str = "day") -> DataFrame:
    """For each left row the columns `take` of the last right row of the same key at the same time or before; null if none.

    Both sides are laid into one stream a key and read in time order.  A key's rows are cut into slices of time, so that a
    very frequent key is read by many tasks; the last right row of each slice is carried over to the slices after it, and
    that table has one row a key and slice.
    """
    part = F.date_trunc(slice_by, F.col(at))
    packed = F.struct(F.col(at).alias("__t"), *take)
    events = right.where(F.col(at).isNotNull()).select(by, F.col(at), packed.alias("__r")).withColumn("__slice", part)
    ends = events.groupBy(by, "__slice").agg(F.max("__r").alias("__last"))
    slices = left.withColumn("__slice", part).select(by, "__slice").distinct().join(ends, [by, "__slice"], "full")
    before = Window.partitionBy(by).orderBy("__slice").rowsBetween(Window.unboundedPreceding, -1)
    carried = slices.select(by, "__slice", F.last("__last", ignorenulls=True).over(before).alias("__carried"))
    rows = left.select("*", F.lit(1).alias("__side"), F.lit(None).cast(events.schema["__r"].dataType).alias("__r")).withColumn("__slice", part)
    both = rows.unionByName(events.withColumn("__side", F.lit(0)), allowMissingColumns=True)
    order = Window.partitionBy(by, "__slice").orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = both.withColumn("__seen", F.last("__r", ignorenulls=True).over(order)).where("__side = 1")
    out = seen.join(carried, [by, "__slice"], "left").withColumn("__best", F.coalesce("__seen", "__carried"))
    return out.select(*left.columns, *(F.col(f"__best.{c}").alias(c) for c in take))
