"""Incremental aggregates of an event stream as matrices: user x type counts by window, and running row sums."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """The events of Parquet files as they arrive, a few files a trigger."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def windowed(events: DataFrame, length: str = "1 hour", late: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """start, user_id, event_type, n, val: one user x type matrix for each window. Rows later than `late` are dropped."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp"))
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return ts.withWatermark("ts", late).groupBy(w.alias("w"), "user_id", "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("val")).select(F.col("w.start").alias("start"), "user_id", "event_type", "n", "val")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """start, stop, user_id, n: sessions of each user that end after a gap."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return ts.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")


def running_row_sums(events: DataFrame) -> DataFrame:
    """rid, val: the sum of values of each user so far, given again whenever it changes. State is two numbers a user."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        total, n = state.get if state.exists else (0.0, 0)
        for pdf in frames:
            total += float(pdf["value"].sum())
            n += len(pdf)
        state.update((total, n))
        yield pd.DataFrame({"rid": [key[0]], "val": [total], "n": [n]})

    return events.groupBy("user_id").applyInPandasWithState(update, "rid long, val double, n long", "total double, n long", "update", "NoTimeout")


def joined_with_static(events: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """A stream of entries joined on a dimension with a matrix that does not change."""
    return events.join(static, F.col(on) == F.col("rid"))
