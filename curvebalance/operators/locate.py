"""Exact point location: by key, by tree descent, or by a plain equi join."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window as W, functions as F

from curvebalance.functions import curves, geometry
from curvebalance.plans import tables
from curvebalance.plans.prefix import with_prefix

from . import kdtree


def _coords(dims: int) -> list[str]:
    return [f"c{i}" for i in range(dims)]


def bin_queries(q: DataFrame, top: kdtree.TopTree) -> DataFrame:
    """Queries with their top cell, brought together by it."""
    b = kdtree.assign_top(q, top)
    return b.repartition("top_id")


def key_buckets(points: DataFrame, dims: int, box, bits: int, bucket_size: int) -> tuple[DataFrame, DataFrame]:
    """Points with key and bucket (equal counts along the curve, equal keys together), and the table bucket, key_lo."""
    k = with_prefix(curves.keyed(points, dims, bits, "morton", box).withColumn("_one", F.lit(1)), "key", "_one", "uid", "rank")
    k = k.withColumn("bucket", F.floor(F.col("rank") / bucket_size)).drop("_one")
    # a key belongs to the bucket of its first point, so a key search finds all of it
    first = k.groupBy("key").agg(F.min("bucket").alias("bucket"))
    k = k.drop("bucket").join(first, "key")
    return k, k.groupBy("bucket").agg(F.min("key").alias("key_lo"))


#: Bucket starts that are searched as a sorted array; more are searched by an as-of window.
SEARCHED = 1 << 20


def by_key(points: DataFrame, q: DataFrame, dims: int, box=None, bits: int = 16, bucket_size: int = 32) -> DataFrame:
    """qid, uid, found of queries (qid, c0..): the query's key is searched among the bucket starts, then its bucket is. Only for the grid
    (cyclic midpoint) curve, on which the key of any point is known without the tree."""
    spark = points.sparkSession
    tables.ship(spark)
    box = box or geometry.bounding_box(points, dims)
    k, starts = key_buckets(points, dims, box, bits, bucket_size)
    k = tables.snapshot(k.select("uid", *_coords(dims), "key", "bucket"), "keyed")
    starts = tables.snapshot(starts.join(k.select("bucket").distinct(), "bucket"), "starts")
    inside = F.lit(True)
    for i, c in enumerate(_coords(dims)):
        inside = inside & F.col(c).between(F.lit(box[i][0]), F.lit(box[i][1]))
    qk = q.withColumn("key", curves.key_of(geometry.quantise(q, dims, box, bits), bits, "morton")).withColumn("_in", inside)
    n = starts.count()
    if n <= SEARCHED:
        rows = sorted((r["key_lo"], r["bucket"]) for r in starts.collect())
        lo, no = np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.int64)

        def run(batches):
            for x in batches:
                i = np.searchsorted(lo, x["key"].to_numpy(), "right") - 1
                yield x.assign(bucket=np.where(i >= 0, no[np.maximum(i, 0)], -1))

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in qk.schema)
        qb = qk.mapInPandas(run, schema + ", bucket long")
    else:
        # two levels: the prefix range of the key, then an as-of window inside it; starts are repeated at the head of each range
        qb = _asof_buckets(qk, starts)
    hit = k.select(F.col("uid"), F.col("bucket"), *[F.col(c).alias(f"p{i}") for i, c in enumerate(_coords(dims))])
    cond = qb["bucket"] == hit["bucket"]
    for i, c in enumerate(_coords(dims)):
        cond = cond & (qb[c] == hit[f"p{i}"])
    cond = cond & qb["_in"]
    j = qb.join(hit, cond, "left")
    return j.select("qid", "uid", F.col("uid").isNotNull().alias("found"))


def _asof_buckets(q: DataFrame, starts: DataFrame, n: int = 256) -> DataFrame:
    from curvebalance.plans.prefix import range_of, ranges

    cuts = ranges(starts, "key_lo", n)
    s = starts.withColumn("_r", range_of(F.col("key_lo"), cuts))
    last = s.groupBy("_r").agg(F.max("key_lo").alias("k"), F.max_by("bucket", "key_lo").alias("bucket"))
    w = W.orderBy("_r").rowsBetween(W.unboundedPreceding, -1)  # one row a range
    every = q.sparkSession.range(len(cuts) + 1).select(F.col("id").cast("int").alias("_r"))  # a range may have queries and no start
    head = every.join(last, "_r", "left").select("_r", F.last("bucket", ignorenulls=True).over(w).alias("head"))
    u = q.withColumn("_r", range_of(F.col("key"), cuts)).withColumn("_b", F.lit(None).cast("long")).withColumn("_side", F.lit(1))
    cols = [c for c in q.columns]
    r = s.select(*[F.col("key_lo").alias("key") if c == "key" else F.lit(None).cast(q.schema[c].dataType).alias(c) for c in cols], "_r", F.col("bucket").alias("_b"), F.lit(0).alias("_side"))
    win = W.partitionBy("_r").orderBy("key", "_side").rowsBetween(W.unboundedPreceding, 0)
    out = u.unionByName(r).withColumn("_b", F.last("_b", ignorenulls=True).over(win)).where("_side = 1").join(F.broadcast(head), "_r", "left")
    return out.select(*cols, F.coalesce("_b", "head", F.lit(-1)).cast("long").alias("bucket"))


def by_tree(tree: kdtree.Tree, q: DataFrame) -> DataFrame:
    """qid, uid, found by descent: the top cell by expression, the subtree built and walked in the cell's task. For any tree."""
    dims, cfg = tree.top.dims, tree.cfg
    cols = _coords(dims)
    tables.ship(q.sparkSession)
    binned = kdtree.assign_top(q.select("qid", *cols), tree.top)

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        empty = pd.DataFrame({"qid": a["qid"].to_numpy(), "uid": pd.array([None] * len(a), dtype="Int64")})
        if not len(a) or not len(b):
            return empty
        top = int(b["top_id"].iloc[0])
        built = kdtree.build_subtree(b["uid"].to_numpy(), b[cols].to_numpy(), cfg, top, kdtree.depth_of(top), want_nodes=True, cell=kdtree._cell(top, dims) if cfg.box == "cell" else None)
        walk = kdtree.TopTree(dims, {kdtree._below(p, top): (d, m) for p, _, d, m, leaf, *_ in built.nodes if not leaf}, {})
        mine = walk.assign_np(a[cols].to_numpy())
        there = pd.DataFrame({"leaf": [kdtree._below(int(p), top) for p in built.path], "uid": b["uid"].to_numpy(), **{c: b[c].to_numpy() for c in cols}})
        j = a.assign(leaf=mine).merge(there, on=["leaf", *cols], how="left")
        return pd.DataFrame({"qid": j["qid"], "uid": j["uid"].astype("Int64")})

    points = tree.members.select("uid", *cols, "top_id")
    return binned.groupBy("top_id").cogroup(points.groupBy("top_id")).applyInPandas(run, "qid long, uid long").select("qid", "uid", F.col("uid").isNotNull().alias("found"))


def by_join(points: DataFrame, q: DataFrame, dims: int) -> DataFrame:
    """The reference: an equi join on all coordinates."""
    return q.select("qid", *_coords(dims)).join(points.select("uid", *_coords(dims)), _coords(dims), "left").select("qid", "uid", F.col("uid").isNotNull().alias("found"))


def auto(tree: kdtree.Tree, points: DataFrame, q: DataFrame, method: str = "auto") -> DataFrame:
    """By key where the curve allows it, by descent elsewhere; asking for keys on another tree is an error."""
    grid = tree.cfg.dim_rule == "cyclic" and tree.cfg.box == "cell" and tree.cfg.curve == "morton"
    if method == "key" and not grid:
        raise ValueError("keys can be searched on cyclic midpoint Morton trees only")
    return by_key(points, q, tree.top.dims) if grid and method != "tree" else by_tree(tree, q)
