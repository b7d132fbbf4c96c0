"""Operations as a stream: mapped, de-duplicated, applied in micro-batches, watched by keyed state."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from curvebalance.operators import dynamic
from curvebalance.plans import tables

#: What an event does to its user's point.
KINDS = {"signup": "insert", "purchase": "insert", "view": "update", "click": "update", "error": "delete"}


def ops_from_events(events: DataFrame) -> DataFrame:
    """op, op_ts, op_id, uid, c0 (value), c1 (seconds of the day), w: a user's point is the user's last event, an error deletes it."""
    op = F.lit(None).cast("string")
    for k, v in KINDS.items():
        op = F.when(F.col("event_type") == k, F.lit(v)).otherwise(op)
    ts = F.col("ts").cast("timestamp")
    second = F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts)
    return events.select(op.alias("op"), ts.alias("op_ts"), F.col("event_id").alias("op_id"), F.col("user_id").alias("uid"), (F.col("value") + 0.0).alias("c0"), second.cast("double").alias("c1"), F.lit(1).cast("long").alias("w")).where("op is not null")


class Snapshots:
    """Versions of the point table in the shared folder: each micro-batch writes the next one, named by its batch id, so that a batch that runs
    again after a failure reads the same version and overwrites the same one."""

    def __init__(self, spark: SparkSession, points: DataFrame):
        self.spark, self.schema, self.base = spark, points.schema, tables.shared_path(spark, "stream")
        points.write.parquet(f"{self.base}/v0")
        self.version = 0

    def read(self, version: int | None = None) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(f"{self.base}/v{self.version if version is None else version}")

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        before = self.read(batch_id)
        dynamic.apply_ops(before, batch).write.mode("overwrite").parquet(f"{self.base}/v{batch_id + 1}")
        self.version = batch_id + 1


def run_batches(ops: DataFrame, points: DataFrame, checkpoint: str) -> Snapshots:
    """Applies a stream of operations to points until the stream's present end."""
    snaps = Snapshots(points.sparkSession, points)
    q = ops.writeStream.foreachBatch(snaps.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return snaps


def deduplicated(ops: DataFrame, delay: str = "1 hour") -> DataFrame:
    return ops.withWatermark("op_ts", delay).dropDuplicatesWithinWatermark(["op_id"])


def bucket_watch(ops: DataFrame, bucket_size: int) -> DataFrame:
    """cell, n, event (split, merge or none) from operations (cell, op): state holds each cell's points and says when it becomes heavy or light."""

    def run(key, batches, state):
        n = state.get[0] if state.exists else 0
        event = "none"
        for x in batches:
            d = int((x["op"] == "insert").sum() - (x["op"] == "delete").sum())
            if n <= 2 * bucket_size < n + d:
                event = "split"
            elif n > bucket_size // 2 >= n + d:
                event = "merge"
            n = max(0, n + d)
        state.update((n,))
        yield pd.DataFrame({"cell": [key[0]], "n": [n], "event": [event]})

    return ops.groupBy("cell").applyInPandasWithState(run, "cell long, n long, event string", "n long", "update", "NoTimeout")


def drain(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream to its present end into a memory table (for tests and small results)."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)
