"""Load over time: tumbling, sliding and session windows, for batches and streams alike."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def watermarked(df: DataFrame, ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    return df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def windowed_load(df: DataFrame, cell: str, size: str, slide: str | None = None, ts: str = "ts") -> DataFrame:
    """cell, start, n of each window."""
    w = F.window(F.col(ts).cast("timestamp"), size, slide) if slide else F.window(F.col(ts).cast("timestamp"), size)
    return df.groupBy(cell, w.alias("win")).agg(F.count("*").alias("n")).select(cell, F.unix_micros("win.start").alias("start_us"), "n")


def session_load(df: DataFrame, cell: str, gap: str, ts: str = "ts") -> DataFrame:
    w = F.session_window(F.col(ts).cast("timestamp"), gap)
    return df.groupBy(cell, w.alias("win")).agg(F.count("*").alias("n")).select(cell, F.unix_micros("win.start").alias("start_us"), "n")


def imbalance_over_time(load: DataFrame) -> DataFrame:
    """start_us, max_n, min_n over cells of a windowed load."""
    return load.groupBy("start_us").agg(F.max("n").alias("max_n"), F.min("n").alias("min_n"))
