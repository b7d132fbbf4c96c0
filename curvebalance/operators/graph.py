"""Sparse matrices and graphs as point sets of their non-zeros, with the partitions to compare."""

from __future__ import annotations

from math import isqrt

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from curvebalance.functions import curves, geometry
from curvebalance.plans import tables

from . import kdtree, slicing


def as_points(coo: DataFrame) -> DataFrame:
    """Non-zeros (row, col, val) as 2-D points; uid = row * 2**31 + col."""
    return coo.select((F.shiftleft(F.col("row"), 31).bitwiseOR(F.col("col"))).alias("uid"), F.col("row").cast("double").alias("c0"), F.col("col").cast("double").alias("c1"), F.lit(1).cast("long").alias("w"))


def bits_for(n: int) -> int:
    return max(1, min(31, (max(1, n) - 1).bit_length()))


def sfc_partition(coo: DataFrame, parts: int, curve: str = "morton", weight: str | None = None) -> DataFrame:
    """Adds part: equal slices of the non-zeros along the curve over (row, col). Loads differ by one non-zero at most."""
    top = coo.agg(F.max(F.greatest("row", "col"))).first()[0] or 0
    bits = bits_for(top + 1)
    key = curves.key_of([F.col("row"), F.col("col")], bits, curve)
    k = coo.withColumn("key", key).withColumn("w", F.col(weight).cast("long") if weight else F.lit(1).cast("long")).withColumn("uid", F.shiftleft(F.col("row"), 31).bitwiseOR(F.col("col")))
    return slicing.slice_curve(k, parts).select("row", "col", "val", "part")


def tree_partition(coo: DataFrame, parts: int, cfg) -> DataFrame:
    """The same along a tree's leaves instead of a grid's cells."""
    p = as_points(coo)
    scaled = geometry.unit_scale(p, 2, geometry.bounding_box(p, 2))
    t = kdtree.tree_order(kdtree.build(scaled, 2, cfg), cfg.curve)
    s = slicing.slice_curve(tables.snapshot(t.select("uid", "key", "w"), "keyed"), parts)
    return coo.withColumn("uid", F.shiftleft(F.col("row"), 31).bitwiseOR(F.col("col"))).join(s.select("uid", "part"), "uid").select("row", "col", "val", "part")


def row_partition(coo: DataFrame, parts: int, rows: int) -> DataFrame:
    """Equal numbers of rows a part."""
    return coo.withColumn("part", F.expr(f"CAST((row * {parts}L) div {rows}L AS INT)"))


def arithmetic_hash(c: Column) -> Column:
    return F.pmod(c * F.lit(kdtree.HASH_A), F.lit(kdtree.HASH_M))


def hash_partition(coo: DataFrame, parts: int, by: str = "row") -> DataFrame:
    """Vertices (rows) or edges to bins by hash: balanced, with much communication."""
    c = F.col("row") if by == "row" else F.col("row") * 31 + F.col("col")
    return coo.withColumn("part", F.pmod(F.shiftright(arithmetic_hash(c), 8), F.lit(parts)).cast("int"))


def grid_partition(coo: DataFrame, parts: int, n: int) -> DataFrame:
    """Blocks of a sqrt(P) by sqrt(P) mesh of an n by n matrix."""
    s = isqrt(parts)
    if s * s != parts:
        raise ValueError("a block mesh needs a square number of parts")
    return coo.withColumn("part", F.expr(f"CAST((row * {s}L) div {n}L * {s} + (col * {s}L) div {n}L AS INT)"))


def partition_vertices(vertices: DataFrame, uid: str, attrs: list[geometry.AttrSpec], parts: int, bits: int = 16) -> DataFrame:
    """Vertices by their attributes in the unit cube: uid, key, part."""
    p = geometry.embed_attributes(vertices, uid, attrs)
    k = curves.keyed(p, len(attrs), min(bits, 63 // len(attrs)), "morton", [(0.0, 1.0)] * len(attrs))
    return slicing.slice_curve(k, parts).select("uid", "key", "part")


def partition_many(matrices: dict[str, DataFrame], parts: int) -> DataFrame:
    """matrix, row, col, val, part for several matrices, each with slices of its own."""
    out = None
    for name, coo in matrices.items():
        p = sfc_partition(coo, parts).select(F.lit(name).alias("matrix"), "row", "col", "val", "part")
        out = p if out is None else out.unionByName(p)
    return out


def bigram_graph(docs: DataFrame) -> DataFrame:
    """row, col, val: a word and its successor within a document, numbered by the words' order. Words are split at single spaces and lower-cased."""
    words = docs.where("text is not null").select("doc_id", F.posexplode(F.split(F.lower("text"), " ")).alias("pos", "word"))
    pair = docs.where("text is not null").select(F.split(F.lower("text"), " ").alias("w")).select(F.explode(F.arrays_zip(F.col("w").alias("a"), F.slice("w", F.lit(2), F.size("w")).alias("b"))).alias("p")).select("p.a", "p.b").where("b is not null")
    ids = vocabulary(words)
    ids = tables.snapshot(ids, "words")
    j = pair.join(ids.select(F.col("word").alias("a"), F.col("id").alias("row")), "a").join(ids.select(F.col("word").alias("b"), F.col("id").alias("col")), "b")
    return j.groupBy("row", "col").agg(F.count("*").alias("val"))


def vocabulary(words: DataFrame) -> DataFrame:
    """word, id: dense numbers in the words' binary order. Counts by the first two characters give offsets, a window inside each the rest."""
    u = words.select("word").distinct().withColumn("_h", F.substring("word", 1, 2))
    heads = u.groupBy("_h").agg(F.count("*").alias("n"))
    # as many rows as there are pairs of characters
    offs = heads.select("_h", F.coalesce(F.sum("n").over(W.orderBy("_h").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("o"))
    return u.join(offs, "_h").select("word", (F.col("o") + F.row_number().over(W.partitionBy("_h").orderBy("word")) - 1).cast("long").alias("id"))
