"""Streams give what batches give."""

import tempfile

from pyspark.sql import functions as F

from curvebalance.operators import dynamic
from curvebalance.sources import io
from curvebalance.streaming import maintain, windows


def test_replay_equals_batch(spark, sf):
    e = io.table(spark, sf, "events")
    d = tempfile.mkdtemp()
    io.write_daily(e.select("event_id", "ts", "user_id", "event_type", "value"), f"{d}/days")
    back = spark.read.parquet(f"{d}/days")
    none = spark.createDataFrame([], "uid long, c0 double, c1 double, w long")
    stream = maintain.ops_from_events(io.daily_stream(spark, f"{d}/days", back.schema, 40))
    snaps = maintain.run_batches(stream, none, f"{d}/ckpt")
    want = sorted(map(tuple, dynamic.apply_ops(none, maintain.ops_from_events(e)).collect()))
    assert sorted(map(tuple, snaps.read().collect())) == want and want


def test_windowed_load_as_stream(spark, sf):
    e = io.table(spark, sf, "events").select("ts", (F.col("user_id") % 4).alias("cell"))
    d = tempfile.mkdtemp()
    e.coalesce(1).write.parquet(f"{d}/in")
    s = spark.readStream.schema(e.schema).parquet(f"{d}/in")
    got = maintain.drain(windows.windowed_load(windows.watermarked(s), "cell", "6 hours"), "loads", "complete", f"{d}/ckpt")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, windows.windowed_load(e, "cell", "6 hours").collect()))


def test_bucket_watch_reports_splits(spark):
    d = tempfile.mkdtemp()
    rows = [(1, "insert")] * 9 + [(2, "insert")] * 3
    spark.createDataFrame(rows, "cell long, op string").coalesce(1).write.parquet(f"{d}/in")
    s = spark.readStream.schema("cell long, op string").parquet(f"{d}/in")
    got = {r["cell"]: (r["n"], r["event"]) for r in maintain.drain(maintain.bucket_watch(s, 4), "watch", "update", f"{d}/ckpt").collect()}
    assert got == {1: (9, "split"), 2: (3, "none")}


def test_repeated_operations_count_once(spark):
    d = tempfile.mkdtemp()
    rows = [(1, "2020-01-01 00:00:00"), (1, "2020-01-01 00:10:00"), (2, "2020-01-01 00:05:00"), (2, "2020-01-01 00:05:00")]
    spark.createDataFrame(rows, "op_id long, op_ts string").select("op_id", F.col("op_ts").cast("timestamp")).coalesce(1).write.parquet(f"{d}/in")
    s = spark.readStream.schema("op_id long, op_ts timestamp").parquet(f"{d}/in")
    got = maintain.drain(maintain.deduplicated(s), "once", "append", f"{d}/ckpt").collect()
    assert sorted(r["op_id"] for r in got) == [1, 2]


def test_imbalance_over_time(spark):
    load = spark.createDataFrame([(1, 0, 5), (2, 0, 3), (1, 60, 4)], "cell long, start_us long, n long")
    assert sorted(map(tuple, windows.imbalance_over_time(load).collect())) == [(0, 5, 3), (60, 4, 4)]
