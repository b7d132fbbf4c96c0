"""Who sends what to whom, in bounded rounds, and the move itself."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F


def plan(before: DataFrame, after: DataFrame, row_bytes: int = 64) -> DataFrame:
    """src, dst, n, bytes between two assignments (uid, part). Inserted ids come from part -1, deleted ones go there."""
    j = before.select("uid", F.col("part").alias("src")).join(after.select("uid", F.col("part").alias("dst")), "uid", "full")
    j = j.select(F.coalesce("src", F.lit(-1)).alias("src"), F.coalesce("dst", F.lit(-1)).alias("dst")).where("src != dst")
    return j.groupBy("src", "dst").agg(F.count("*").alias("n")).withColumn("bytes", F.col("n") * F.lit(row_bytes).cast("long"))


def rounds(transfers: DataFrame, max_bytes: int, row_bytes: int = 64) -> DataFrame:
    """src, dst, round, n: each transfer cut into messages of at most max_bytes (one row at least)."""
    per = max(1, max_bytes // row_bytes)
    r = transfers.withColumn("round", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / per).cast("long"))))
    return r.select("src", "dst", "round", F.least(F.lit(per).cast("long"), F.col("n") - F.col("round") * per).alias("n"))


def row_rounds(rows: DataFrame, max_bytes: int) -> DataFrame:
    """The round of every moving row (src, dst, uid, bytes): its prefix of bytes within the pair over the limit."""
    w = W.partitionBy("src", "dst").orderBy("uid").rowsBetween(W.unboundedPreceding, -1)
    return rows.withColumn("round", F.floor(F.coalesce(F.sum("bytes").over(w), F.lit(0)) / max_bytes).cast("long"))


def exchange(payload: DataFrame, assigned: DataFrame, files_a_part: int = 1) -> DataFrame:
    """The payload (uid, ...) in its slices, each sorted along the curve. A slice may span several tasks: many of them, if it is large."""
    j = payload.join(assigned.select("uid", "key", "part"), "uid")
    salt = F.pmod(F.xxhash64("uid"), F.lit(files_a_part))
    return j.repartition(F.col("part"), salt).sortWithinPartitions("part", "key", "uid")


def reorder(payload: DataFrame, order: DataFrame) -> DataFrame:
    """The payload in the order of a permutation (uid, rank)."""
    return payload.join(order.select("uid", "rank"), "uid").repartitionByRange("rank").sortWithinPartitions("rank")


def neighbour_share(moves: DataFrame) -> float:
    """The share of moved points that went to the next or the previous slice, from (step_size, n)."""
    r = moves.where("step_size != 0").agg(F.sum("n").alias("all"), F.sum(F.when(F.abs("step_size") == 1, F.col("n"))).alias("near")).first()
    return 1.0 if not r["all"] else (r["near"] or 0) / r["all"]
