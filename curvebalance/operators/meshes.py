"""Mesh elements as indivisible points, and their dual graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def centroids(nodes: DataFrame, element: str, coords: list[str]) -> DataFrame:
    """element, c0.., w: the centre of gravity stands for an element, its number of nodes is its weight."""
    return nodes.groupBy(F.col(element).alias("element")).agg(*[F.avg(c).alias(f"c{i}") for i, c in enumerate(coords)], F.count("*").alias("w"))


def element_parts(nodes: DataFrame, element: str, assigned: DataFrame) -> DataFrame:
    """Nodes with the part of their element: no element is ever cut."""
    return nodes.join(assigned.select(F.col("uid").alias(element), "part"), element)


def dual_graph(nodes: DataFrame, element: str, node: str, most: int | None = None) -> DataFrame:
    """src, dst, w: elements that share nodes, by an equi self join. A node with more than `most` elements joins them in a ring instead
    of all pairs, which keeps them connected; None makes all pairs."""
    n = nodes.select(F.col(element).alias("e"), F.col(node).alias("n")).distinct()
    if most is None:
        a, b = n.withColumnRenamed("e", "src"), n.withColumnRenamed("e", "dst")
        return a.join(b, "n").where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("w"))
    from pyspark.sql import Window as W

    size = n.groupBy("n").agg(F.count("*").alias("k"))
    n = n.join(size, "n")
    small = n.where(F.col("k") <= most)
    pairs = small.select("n", F.col("e").alias("src")).join(small.select("n", F.col("e").alias("dst")), "n").where("src < dst").select("src", "dst")
    ring = n.where(F.col("k") > most).withColumn("dst", F.lead("e").over(W.partitionBy("n").orderBy("e"))).where("dst is not null").select(F.col("e").alias("src"), "dst")
    return pairs.unionByName(ring).groupBy("src", "dst").agg(F.count("*").alias("w"))
