"""Trees of points that change: operations on buckets, splits of heavy and merges of light ones, and the step driver."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window as W, functions as F

from curvebalance.plans import tables
from curvebalance.plans.specs import TreeConfig

from . import amortise, balance, kdtree, slicing


def route(ops: DataFrame, top: kdtree.TopTree) -> DataFrame:
    """Operations (step, op, op_ts, uid, c0.., w) with the top cell they go to."""
    return kdtree.assign_top(ops, top)


def last_ops(ops: DataFrame) -> DataFrame:
    """The last operation of each id wins, by (op_ts, op_id)."""
    w = W.partitionBy("uid").orderBy(F.desc("op_ts"), F.desc("op_id"))
    return ops.withColumn("_rn", F.row_number().over(w)).where("_rn = 1").drop("_rn")


def apply_ops(points: DataFrame, ops: DataFrame) -> DataFrame:
    """Points after inserts, updates (insert if absent) and deletes (nothing if absent): one anti join and one union. Inner nodes are not touched."""
    o = last_ops(ops)
    stay = points.join(o.select("uid"), "uid", "left_anti")
    return stay.unionByName(o.where("op != 'delete'").select(*points.columns))


def adjust_nodes(leaves: dict[int, tuple[int, int]], bucket_size: int) -> dict[int, int]:
    """Where each leaf (path -> (depth, n)) of one subtree goes when light siblings merge: empty leaves are dropped, a pair of leaf siblings
    that fit one bucket merges, an only child that is a leaf and fits is lifted. Post-order, so a merged node may merge again."""
    to = {p: p for p, (_, n) in leaves.items() if n > 0}
    size = {p: leaves[p][1] for p in to}
    open_ = {a for p in to for a in _ancestors(p)}
    for p in sorted(open_, key=lambda q: -q.bit_length()):
        kids = [q for q in (2 * p, 2 * p + 1) if q in size]
        inner = [q for q in (2 * p, 2 * p + 1) if q in open_ and q not in size]
        if kids and not inner and sum(size[q] for q in kids) <= bucket_size:
            size[p] = sum(size.pop(q) for q in kids)
            for x, y in to.items():
                if y in kids:
                    to[x] = p
    return to


def _ancestors(p: int):
    while p > 1:
        p >>= 1
        yield p


def adjust(members: DataFrame, dims: int, cfg: TreeConfig) -> DataFrame:
    """members (uid, c0.., w, top_id, path, depth) with heavy buckets (over 2B) split until they hold B, and light ones merged. One task a top cell."""
    tables.ship(members.sparkSession)
    cols = [f"c{i}" for i in range(dims)]

    def run(g: pd.DataFrame) -> pd.DataFrame:
        top = int(g["top_id"].iloc[0])
        path, depth = g["path"].to_numpy().copy(), g["depth"].to_numpy().copy()
        c, uid = g[cols].to_numpy(), g["uid"].to_numpy()
        for p in np.unique(path):
            at = np.flatnonzero(path == p)
            if len(at) > 2 * cfg.bucket_size:
                b = kdtree.build_subtree(uid[at], c[at], cfg, int(p), kdtree.depth_of(int(p)))
                path[at], depth[at] = b.path, b.depth
        u, n = np.unique(path, return_counts=True)
        low = {kdtree._below(int(p), top): (0, int(k)) for p, k in zip(u, n)}
        to = adjust_nodes(low, cfg.bucket_size)
        full = {int(p): _above(to[kdtree._below(int(p), top)], top) for p in u}
        path = np.array([full[int(p)] for p in path], np.int64)
        return g.assign(path=path, depth=np.array([kdtree.depth_of(int(p)) for p in path], np.int32))

    schema = "uid long, " + ", ".join(f"{c} double" for c in cols) + ", w long, top_id long, path long, depth int"
    return members.select("uid", *cols, "w", "top_id", "path", "depth").groupBy("top_id").applyInPandas(run, schema)


def _above(below: int, top: int) -> int:
    k = kdtree.depth_of(below)
    return top << k | below & (1 << k) - 1


def merge_light(leaves: DataFrame, bucket_size: int) -> DataFrame:
    """The merges alone on a table of leaves (path, depth, n): each leaf with points goes to the highest ancestor whose points fit one bucket, or
    stays if it does not fit itself. Bottom-up merging of leaf siblings and lifting of only children end there: if a node's points fit,
    so do its children's, and they are leaves by then. One aggregate over the leaves' ancestors."""
    full = leaves.where("n > 0").select("path", "depth", "n")
    sums = kdtree.roll_up(full, {"n": F.sum}).where(F.col("n") <= bucket_size).select(F.col("path").alias("up"), F.col("depth").alias("up_depth"))
    up = full.withColumn("_k", F.explode(F.sequence(F.lit(0), F.col("depth")))).withColumn("up", F.expr("shiftright(path, _k)"))
    best = up.join(sums, "up").groupBy("path").agg(F.min(F.struct("up_depth", "up")).alias("to"))
    to = full.join(best, "path", "left").select(F.coalesce("to.up", "path").alias("path"), F.coalesce("to.up_depth", "depth").alias("depth"), "n")
    return to.groupBy("path", "depth").agg(F.sum("n").alias("n"))


def place(points: DataFrame, leaves: DataFrame) -> DataFrame:
    """Points that already have a path, with that path lifted to the leaf that now covers it."""
    up = points.withColumn("_a", F.explode(F.sequence(F.lit(0), F.col("depth")))).withColumn("leaf", F.expr("shiftright(path, _a)"))
    return up.join(leaves.select(F.col("path").alias("leaf"), F.col("depth").alias("leaf_depth")), "leaf").drop("_a")


def model_time(members: DataFrame, ops: DataFrame) -> DataFrame:
    """A clock that any engine can reproduce: a row a top cell with its operations, buckets and time (operations plus a tenth a bucket visited)."""
    o = ops.groupBy("top_id").agg(F.count("*").alias("n_ops"))
    b = members.groupBy("top_id").agg(F.count_distinct("path").alias("buckets"))
    return b.join(o, "top_id", "full").select("top_id", F.coalesce("n_ops", F.lit(0)).alias("n_ops"), F.coalesce("buckets", F.lit(0)).alias("buckets")).withColumn("time", F.col("n_ops") + F.col("buckets") * 0.1)


def run(points: DataFrame, dims: int, cfg: TreeConfig, parts: int, source: Callable[[int], DataFrame | None], steps: int, adjust_every: int = 5, clock: str = "model", policy: str = "amortised", mode: str = "full") -> tuple[DataFrame, list[dict]]:
    """Steps of operations on a tree, adjustments every few steps, and a rebalance when the controller says so. Returns members (uid, c0.., w, top_id,
    path, depth, part) and the trace.

    A rebalance builds the tree anew and cuts its curve (full), or only re-cuts the curve that is there (incremental). A new point gets the part of
    its leaf's first point, or of its top cell's, until then. Lineage ends at every step in a snapshot. The trace has counts, the heaviest and mean load after
    each step, and wall seconds of deletion, insertion, adjustment and balancing.
    """
    cols = [f"c{i}" for i in range(dims)]
    t0 = time.perf_counter()

    def built(p: DataFrame):
        tree = kdtree.build(p.select("uid", *cols, "w"), dims, cfg)
        m = tables.snapshot(tree.members, "members")
        return tree, cut(m), tables.snapshot(kdtree.split_planes(m, dims, cfg), "planes")

    def cut(m: DataFrame) -> DataFrame:
        keyed = tables.snapshot(m.withColumn("key", kdtree.leaf_key(F.col("path"), F.col("depth"))).select("uid", "key", "w"), "keyed")
        part = balance.incremental(keyed, None, parts).assigned.select("uid", "part")
        return tables.snapshot(m.drop("part").join(part, "uid"), "members")

    tree, members, planes = built(points)
    buckets, n = members.select("path").distinct().count(), members.count()
    spent = time.perf_counter() - t0
    ctl = amortise.Controller(balance_cost=float(n) / 100 if clock == "model" else spent, buckets=buckets, policy=policy)
    for step in range(steps):
        t = [time.perf_counter()]
        ops, n_in, n_out, moved = source(step), 0, 0, 0
        if ops is not None:
            ops = tables.snapshot(route(last_ops(ops), tree.top), "ops")
            n_out, n_in = ops.where("op = 'delete'").count(), ops.where("op != 'delete'").count()
            members = tables.snapshot(members.join(ops.select("uid"), "uid", "left_anti"), "members")
        t.append(time.perf_counter())
        if ops is not None:
            new = ops.where("op != 'delete'").select("uid", *cols, "w", "top_id")
            new = locate_leaf(new, members, planes, dims)
            near = members.groupBy("path").agg(F.min_by("part", "uid").alias("a"))
            wide = members.groupBy("top_id").agg(F.min_by("part", "uid").alias("b"))
            new = new.join(near, "path", "left").join(wide, "top_id", "left").withColumn("part", F.coalesce("a", "b", F.lit(0))).select(*members.columns)
            members = tables.snapshot(members.unionByName(new), "members")
        t.append(time.perf_counter())
        adjusted = (step + 1) % adjust_every == 0
        if adjusted:
            planes = tables.snapshot(planes.unionByName(heavy_planes(members, dims, cfg)).dropDuplicates(["path"]), "planes")
            members = tables.snapshot(adjust(members, dims, cfg).join(members.select("uid", "part"), "uid"), "members")
        t.append(time.perf_counter())
        per = model_time(members, ops) if ops is not None else None
        row = per.agg(F.max("time").alias("t"), F.max("buckets").alias("b")).first() if per is not None else None
        now = ctl.observe(row["t"] if clock == "model" and row else t[-1] - t[0], max(1, n_in + n_out), row["b"] if row else None)
        if now:
            t1, before = time.perf_counter(), members.select("uid", F.col("part").alias("old"))
            if mode == "full":
                tree, members, planes = built(members)
            else:
                members = cut(members)
            moved = members.join(before, "uid").where("part != old").count()
            ctl.rebalanced(float(members.count()) / 100 if clock == "model" else time.perf_counter() - t1)
        t.append(time.perf_counter())
        load = slicing.loads(members, parts).agg(F.max("w").alias("hi"), F.avg("w").alias("mean")).first()
        ctl.trace[-1] |= {"n_ops": n_in + n_out, "inserted": n_in, "deleted": n_out, "adjusted": adjusted, "moved": moved, "load_max": load["hi"], "load_mean": load["mean"], "buckets_max": row["b"] if row else None, "time_max": row["t"] if row else t[-1] - t[0]}
        ctl.trace[-1] |= dict(zip(("delete_s", "insert_s", "adjust_s", "balance_s"), (y - x for x, y in zip(t, t[1:])))) | {"build_s": spent}
    return members, ctl.trace


def heavy_planes(members: DataFrame, dims: int, cfg: TreeConfig) -> DataFrame:
    """The planes of the splits that `adjust` makes of heavy buckets."""
    heavy = members.groupBy("path").agg(F.count("*").alias("n")).where(F.col("n") > 2 * cfg.bucket_size).select(F.col("path").alias("root"))
    rows = members.join(tables.maybe_broadcast(heavy, 16), members["path"] == heavy["root"]).select("root", "uid", *[f"c{i}" for i in range(dims)], "top_id")
    tops = rows.select("root", "top_id").distinct()
    return kdtree.split_planes(rows, dims, cfg, "root").join(tops, "root").select("top_id", "path", "dim", "value")


def locate_leaf(new: DataFrame, members: DataFrame, planes: DataFrame, dims: int) -> DataFrame:
    """New points (uid, c0.., w, top_id) with the leaf that the descent from their top cell ends at: a present leaf, or a node without a plane, whose points
    had all gone. One task a top cell."""
    cols = [f"c{i}" for i in range(dims)]
    tables.ship(members.sparkSession)
    leaves = members.select("top_id", "path").distinct().select("top_id", "path", F.lit(-1).alias("dim"), F.lit(0.0).alias("value"))
    nodes = planes.select("top_id", "path", "dim", "value").unionByName(leaves)

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a):
            return a.assign(path=np.zeros(0, np.int64), depth=np.zeros(0, np.int32))
        top, is_leaf = int(a["top_id"].iloc[0]), b["dim"] < 0
        ends = set(b["path"][is_leaf].tolist())
        inner = {kdtree._below(int(p), top): (int(d), float(v)) for p, d, v in zip(*(b.loc[~is_leaf, c] for c in ("path", "dim", "value"))) if int(p) not in ends}
        at = kdtree.TopTree(dims, inner, {}).assign_np(a[cols].to_numpy()) if inner else np.ones(len(a), np.int64)
        path = np.array([_above(int(p), top) for p in at], np.int64)
        return a.assign(path=path, depth=np.array([kdtree.depth_of(int(p)) for p in path], np.int32))

    schema = "uid long, " + ", ".join(f"{c} double" for c in cols) + ", w long, top_id long, path long, depth int"
    return new.select("uid", *cols, "w", "top_id").groupBy("top_id").cogroup(nodes.groupBy("top_id")).applyInPandas(run, schema)
