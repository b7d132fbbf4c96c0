"""Boxes, scaling, quantisation, distances and encodings of attributes, as column expressions."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from curvebalance.plans.specs import PointSpec


def as_points(df: DataFrame, spec: PointSpec, check_unique: bool = False) -> DataFrame:
    """uid, c0.., w: the compact view that all methods work on. -0.0 becomes 0.0; null or NaN coordinates and null ids are an error."""
    spec.check(df)

    def number(c: str) -> Column:
        kind = df.schema[c].dataType.typeName()
        if kind == "date":
            return F.datediff(F.col(c), F.lit("1970-01-01").cast("date")).cast("double")
        if kind.startswith("timestamp"):
            return F.unix_micros(F.col(c).cast("timestamp")).cast("double")
        return F.col(c).cast("double")

    bad = lambda c: F.raise_error(F.lit(f"column {c} has a value that is no coordinate"))
    coords = [F.when(number(c).isNull() | F.isnan(number(c)), bad(c)).otherwise(number(c) + F.lit(0.0)).alias(f"c{i}") for i, c in enumerate(spec.coords)]
    uid = F.when(F.col(spec.uid).isNull(), F.raise_error(F.lit("an id is null"))).otherwise(F.col(spec.uid).cast("long"))
    w = F.col(spec.weight).cast("long") if spec.weight else F.lit(1).cast("long")
    out = df.select(uid.alias("uid"), *coords, w.alias("w"))
    if check_unique and not out.groupBy("uid").count().where("count > 1").isEmpty():
        raise ValueError("ids are not unique")
    return out


def bounding_box(df: DataFrame, dims: int, by: str | None = None):
    """[(lo, hi)] of every dimension (None, if there are no points), or a table of boxes by a column."""
    aggs = [f(f"c{i}").alias(f"{n}{i}") for i in range(dims) for n, f in (("lo", F.min), ("hi", F.max))]
    if by is not None:
        return df.groupBy(by).agg(*aggs)
    r = df.agg(*aggs).first()
    return None if r is None or r[0] is None else [(r[f"lo{i}"], r[f"hi{i}"]) for i in range(dims)]


def scaled(c: Column, lo: float, hi: float) -> Column:
    """To [0, 1]; a box without width gives 0."""
    return (c - F.lit(lo)) / F.lit(hi - lo) if hi > lo else F.lit(0.0)


def unit_scale(df: DataFrame, dims: int, box) -> DataFrame:
    return df.select("uid", *[scaled(F.col(f"c{i}"), *box[i]).alias(f"c{i}") for i in range(dims)], "w") if box else df


def quantised(c: Column, lo: float, hi: float, bits: int) -> Column:
    """Grid cell of a coordinate: 2**bits cells over the box, the upper end in the last one."""
    return F.least(F.floor(scaled(c, lo, hi) * F.lit(float(1 << bits))).cast("long"), F.lit((1 << bits) - 1)) if hi > lo else F.lit(0).cast("long")


def quantise(df: DataFrame, dims: int, box, bits: int) -> list[Column]:
    return [quantised(F.col(f"c{i}"), *(box[i] if box else (0.0, 0.0)), bits) for i in range(dims)]


def distance(a: list[Column], b: list[Column], kind: str = "l2", weights: list[float] | None = None) -> Column:
    """l2 is squared: it orders alike and needs no root."""
    d = [x - y for x, y in zip(a, b)]
    w = [F.lit(float(x)) for x in weights] if weights else [F.lit(1.0)] * len(d)
    if kind == "l1":
        return reduce(lambda x, y: x + y, [F.abs(x) * v for x, v in zip(d, w)])
    if kind == "linf":
        parts = [F.abs(x) * v for x, v in zip(d, w)]
        return F.greatest(*parts) if len(parts) > 1 else parts[0]
    if kind in ("l2", "weighted"):
        return reduce(lambda x, y: x + y, [x * x * v for x, v in zip(d, w)])
    raise ValueError(f"unknown distance: {kind}")


@dataclass(frozen=True)
class AttrSpec:
    """A vertex attribute as a coordinate. encoder: number, or category (dense rank of its values); scale: the share of the unit
    interval that its range takes, its weight in distances."""

    name: str
    encoder: str = "number"
    scale: float = 1.0


def embed_attributes(df: DataFrame, uid: str, attrs: list[AttrSpec], weight: str | None = None) -> DataFrame:
    """uid, c0.., w in the unit cube. Categories are ranked through a table of their distinct values."""
    out = df
    for i, a in enumerate(attrs):
        if a.encoder == "category":
            # a dimension of a vertex is a small domain; its size is checked like any broadcast
            from pyspark.sql import Window as W

            from curvebalance.plans.tables import maybe_broadcast

            values = df.select(F.col(a.name).alias("_v")).where("_v is not null").distinct()
            ranks = values.withColumn(f"_k{i}", (F.row_number().over(W.orderBy("_v"))).cast("double"))
            out = out.join(maybe_broadcast(ranks, 64), out[a.name] == F.col("_v"), "left").drop("_v").withColumn(f"_k{i}", F.coalesce(f"_k{i}", F.lit(0.0)))
        else:
            out = out.withColumn(f"_k{i}", F.coalesce(F.col(a.name).cast("double") + F.lit(0.0), F.lit(0.0)))
    pts = out.select(F.col(uid).cast("long").alias("uid"), *[F.col(f"_k{i}").alias(f"c{i}") for i in range(len(attrs))], (F.col(weight).cast("long") if weight else F.lit(1).cast("long")).alias("w"))
    box = bounding_box(pts, len(attrs))
    if box is None:
        return pts
    return pts.select("uid", *[(scaled(F.col(f"c{i}"), *box[i]) * F.lit(float(a.scale))).alias(f"c{i}") for i, a in enumerate(attrs)], "w")
