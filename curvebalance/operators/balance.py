"""Full, incremental and automatic balancing."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from curvebalance.functions import curves
from curvebalance.plans import tables
from curvebalance.plans.specs import TreeConfig

from . import kdtree, slicing


@dataclass
class Balance:
    """An assignment (uid, key, w, prefix, part) that can be re-cut without building anything again."""

    assigned: DataFrame
    parts: int
    kind: str


def full(points: DataFrame, dims: int, parts: int, cfg: TreeConfig | None = None, bits: int = 16, rule: str = "prefix") -> Balance:
    """Build, traverse, slice. Without a tree config the curve is that of the grid: a projection and one shuffle by range; with one, a
    tree of scaled points is built and its leaves are the order. Ties within a leaf go by id."""
    if cfg is None:
        keyed = curves.keyed(points, dims, bits)
    else:
        keyed = kdtree.tree_order(kdtree.build(points, dims, cfg), cfg.curve)
    keyed = tables.snapshot(keyed.select("uid", "key", "w"), "keyed")
    return Balance(slicing.slice_curve(keyed, parts, rule), parts, "full")


def incremental(prev: DataFrame, weights: DataFrame | None, parts: int, rule: str = "prefix") -> Balance:
    """New ranks and slices on the existing curve (uid, key): with new weights (uid, w), or those it has. No tree work."""
    keyed = prev.select("uid", "key", "w")
    if weights is not None:
        keyed = keyed.drop("w").join(weights.select("uid", "w"), "uid")
    return Balance(slicing.slice_curve(keyed, parts, rule), parts, "incremental")


def misshapen(shape_now: float, shape_after_full: float, limit: float = 2.0) -> bool:
    """Whether parts have lost their shape: mean surface to volume against that right after the last full balance."""
    return shape_now > limit * shape_after_full


def auto(points: DataFrame, prev: DataFrame, weights: DataFrame, dims: int, parts: int, shape, last_shape: float, limit: float = 2.0, cfg: TreeConfig | None = None) -> Balance:
    """Incremental, unless its parts are misshapen by `shape` (assignment -> mean surface to volume); then full."""
    b = incremental(prev, weights, parts)
    return full(points, dims, parts, cfg) if misshapen(shape(b.assigned), last_shape, limit) else b


def moved(before: DataFrame, after: DataFrame) -> DataFrame:
    """step_size (new part less old), n of all ids in both."""
    j = before.select("uid", F.col("part").alias("a")).join(after.select("uid", F.col("part").alias("b")), "uid")
    return j.groupBy((F.col("b") - F.col("a")).alias("step_size")).agg(F.count("*").alias("n"))
