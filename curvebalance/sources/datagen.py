"""Generated points: uniform, clustered and regular meshes, the same in any engine because they come from arithmetic hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from curvebalance.operators.kdtree import HASH_M, hash_unit


def unit(i: int):
    """A reproducible number in [0, 1) of a row's id for coordinate i."""
    return hash_unit(F.col("id") * 16 + (i + 1)) / F.lit(float(HASH_M))


def uniform(spark: SparkSession, n: int, dims: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("uid"), *[unit(i).alias(f"c{i}") for i in range(dims)], F.lit(1).cast("long").alias("w"))


def clustered(spark: SparkSession, n: int, dims: int, power: int = 3, mix: float = 0.5) -> DataFrame:
    """A share of the points is drawn towards the low corner by a power of its coordinates; the rest stays uniform."""
    near = F.pmod(F.col("id"), F.lit(1000)) < int(1000 * mix)
    return spark.range(n).select(F.col("id").alias("uid"), *[F.when(near, F.pow(unit(i), F.lit(float(power)))).otherwise(unit(i)).alias(f"c{i}") for i in range(dims)], F.lit(1).cast("long").alias("w"))


def mesh(spark: SparkSession, side: int, dims: int) -> DataFrame:
    """uid, g0..: a regular grid of side**dims cells."""
    return spark.range(side**dims).select(F.col("id").alias("uid"), *[F.expr(f"(id div {side ** (dims - 1 - i)}L) % {side}L").alias(f"g{i}") for i in range(dims)])


def replicate(points: DataFrame, k: int, dims: int) -> DataFrame:
    """k copies of a point set, each moved a little, for scale trials."""
    return points.withColumn("_k", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).select((F.col("uid") * k + F.col("_k")).alias("uid"), *[(F.col(f"c{i}") + F.col("_k") * 1e-9).alias(f"c{i}") for i in range(dims)], "w")
