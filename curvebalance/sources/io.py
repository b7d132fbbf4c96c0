"""Readers and writers: tables, edge lists, sliced and sorted layouts, streams of daily files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str) -> DataFrame:
    """row, col of a tab-separated edge list with # comments."""
    return spark.read.csv(path, sep="\t", comment="#", schema="row long, col long").where("row is not null and col is not null")


def write_edges(edges: DataFrame, path: str) -> None:
    edges.select("row", "col").write.csv(path, sep="\t")


def write_slices(df: DataFrame, path: str, sort: str = "key") -> None:
    """One folder a slice, files sorted along the curve, so slices are pruned by folder and boxes by the files' statistics."""
    df.repartition("part").sortWithinPartitions("part", sort).write.partitionBy("part").parquet(path)


def write_sorted(df: DataFrame, path: str, key: str = "key", files: int = 64) -> None:
    df.repartitionByRange(files, key).sortWithinPartitions(key).write.parquet(path)


def write_bucketed(df: DataFrame, name: str, by: str, buckets: int) -> None:
    """A bucketed table: joins on its key need no shuffle of it."""
    df.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").saveAsTable(name)


def write_daily(events: DataFrame, path: str, ts: str = "ts") -> None:
    """One file a day, to be replayed as a stream."""
    events.withColumn("day", F.to_date(ts)).repartition("day").sortWithinPartitions(ts).write.partitionBy("day").parquet(path)


def daily_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
