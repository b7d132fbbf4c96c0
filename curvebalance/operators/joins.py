"""Range and as-of joins from equi joins and windows: Spark has neither as an operator."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F


def range_join(points: DataFrame, key: str, ranges: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Rows of points with each range [lo, hi] they fall in: both sides go to blocks of `width` keys, an equi join meets them, a filter decides.
    A range spans (hi - lo) / width + 1 blocks."""
    a = points.withColumn("_b", F.floor(F.col(key) / width))
    b = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return a.join(b, "_b").where((F.col(key) >= F.col(lo)) & (F.col(key) <= F.col(hi))).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, key: str, value: str, by: str) -> DataFrame:
    """left with the value of the last row of `right` in its group whose key is not greater: one union and one window a group, no product."""
    cols = left.columns
    u = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1))
    r = right.select(*[F.col(c) if c in (key, by) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = W.partitionBy(by).orderBy(key, "_side").rowsBetween(W.unboundedPreceding, 0)
    return u.unionByName(r).withColumn(value, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")
