"""Joins of event tables on time: as-of, interval and range joins without pairs of a whole group."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """left with the last value of right of the same key at or before its time (NULL if none).

    One union, one sort a key: the running last value meets each left row, so no pair of rows is ever made.
    """
    names = left.columns
    both = left.withColumn("__v", F.lit(None).cast(dict(right.dtypes)[value])).withColumn("__left", F.lit(True))
    other = right.select(key, ts, F.col(value).alias("__v"), F.lit(False).alias("__left"))
    w = Window.partitionBy(key).orderBy(ts, "__left").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.unionByName(other, allowMissingColumns=True).withColumn("__v", F.last("__v", ignorenulls=True).over(w))
    return filled.filter("__left").select(*names, F.col("__v").alias(f"{value}_as_of"))


def within(points: DataFrame, spans: DataFrame, key: str, ts: str, start: str, stop: str, width: str = "1 hour") -> DataFrame:
    """Points joined with the spans [start, stop) of the same key that hold them.

    Spans are listed in the buckets that they touch, points in their own, so the join is an equi-join with a filter. The
    width should be near the usual length of a span.
    """
    seconds = F.lit(_seconds(width))
    bucket = lambda c: F.floor(F.col(c).cast("timestamp").cast("long") / seconds)
    listed = spans.withColumn("__b", F.explode(F.sequence(bucket(start), bucket(stop))))
    return points.withColumn("__b", bucket(ts)).join(listed, [key, "__b"]).filter((F.col(ts) >= F.col(start)) & (F.col(ts) < F.col(stop))).drop("__b")


def _seconds(width: str) -> int:
    n, unit = width.split()
    return int(n) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s")]


def in_range(cells: DataFrame, ranges: DataFrame) -> DataFrame:
    """Entries joined with ranges (lo, hi, name) of values that hold them; ranges are few and broadcast."""
    return cells.join(F.broadcast(ranges), F.col("val").between(F.col("lo"), F.col("hi")))
