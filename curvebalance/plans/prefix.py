"""Prefix sums over a global order without a window over the whole table.

Rows are cut into contiguous ranges of the order, as many as their number asks for. Range totals (one row each) give offsets by a window over that small
table; a window inside each range gives the rest. Up to `CUTS` ranges are cut at approximate quantiles of the key, by an expression, and the shuffle by
range is the only one of the size of the data. More ranges, or ranges of which one key overfills one, come from a range partitioning by key and tie, written
once, so that equal keys are split and no task has much more than its share.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .tables import snapshot


#: Rows of a range, ranges that an expression may tell apart, and how far a range may exceed its share.
RANGE_ROWS, CUTS, OVERFULL = 250_000, 256, 8
#: Ranges of the first cut, which serve up to FIRST * RANGE_ROWS rows.
FIRST = 64


def ranges(df: DataFrame, key: str, n: int) -> list:
    """At most n - 1 cuts of a numeric key, as exact values of the key's type."""
    if n < 2:
        return []
    return sorted(set(df.stat.approxQuantile(key, [i / n for i in range(1, n)], min(0.01, 0.25 / n))))


def range_of(key: Column, cuts: list) -> Column:
    """How many cuts lie below the key: a binary decision tree of literals, compiled with the rest of the stage."""

    def node(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(key <= F.lit(int(cuts[mid]) if float(cuts[mid]).is_integer() else cuts[mid]), node(lo, mid)).otherwise(node(mid + 1, hi))

    return node(0, len(cuts))


def with_prefix(df: DataFrame, key: str, value: str, tie: str, out: str = "prefix", n: int | None = None, rank: str | None = None) -> DataFrame:
    """Adds the exclusive prefix sum of `value` in the order (key, tie) and, if named, the rank (from 0). `n`: ranges; by default as many as the rows fill."""
    b, n, fixed = None, n or FIRST, n is not None
    while b is None and n <= CUTS:
        b = df.withColumn("_r", range_of(F.col(key), ranges(df, key, n)))
        sums = b.groupBy("_r").agg(F.sum(value).alias("_s"), F.count("*").alias("_n"))
        found = sums.collect()  # at most n rows
        need = -(-sum(r["_n"] for r in found) // RANGE_ROWS)
        if not fixed and need > n:  # a second cut knows the number of rows
            b, n = None, need
        elif max((r["_n"] for r in found), default=0) > OVERFULL * RANGE_ROWS:
            b, n = None, max(need, CUTS + 1)  # one key holds most of a range
        else:
            sums = df.sparkSession.createDataFrame(found, sums.schema)
    if b is None:
        b = snapshot(df.repartitionByRange(n, key, tie).withColumn("_r", F.spark_partition_id()), "ranges")
        sums = b.groupBy("_r").agg(F.sum(value).alias("_s"), F.count("*").alias("_n"))
    w = W.orderBy("_r").rowsBetween(W.unboundedPreceding, -1)  # at most n rows
    offs = sums.select("_r", F.coalesce(F.sum("_s").over(w), F.lit(0)).alias("_o"), F.coalesce(F.sum("_n").over(w), F.lit(0)).alias("_k"))
    inner = W.partitionBy("_r").orderBy(key, tie)
    res = b.join(F.broadcast(offs), "_r").withColumn(out, F.col("_o") + F.coalesce(F.sum(value).over(inner.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    if rank:
        res = res.withColumn(rank, F.col("_k") + F.row_number().over(inner) - 1)
    return res.drop("_r", "_o", "_k")
