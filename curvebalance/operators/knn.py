"""k nearest neighbours: approximate by the curve, by subtree, and exact."""

from __future__ import annotations

from collections.abc import Callable
from math import ceil, inf, log2

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window as W, functions as F

from curvebalance.functions import curves, geometry
from curvebalance.plans import tables
from curvebalance.plans.prefix import CUTS, range_of, ranges, with_prefix

from . import kdtree

#: Queries that a task searches side by side, points of a chunk of the curve, of a block and of a cell that bounds a distance, and children of a node of boxes.
EXACT_QUERIES, CHUNK, BLOCK, CELL, FAN = 5000, 100_000, 32, 64, 8


def _rank(cand: DataFrame, k: int) -> DataFrame:
    rn = F.row_number().over(W.partitionBy("qid").orderBy("d2", "uid"))
    return cand.withColumn("rn", rn).where(F.col("rn") <= k).select("qid", "rn", "uid", F.round("d2", 12).alias("d2"))


def buckets(keyed: DataFrame, size: int) -> DataFrame:
    """Equal-count buckets along the curve: bucket = rank div size."""
    k = with_prefix(keyed.withColumn("_one", F.lit(1)), "key", "_one", "uid", "rank")
    return k.withColumn("bucket", F.expr(f"rank div {size}")).drop("_one")


def by_curve(points: DataFrame, q: DataFrame, dims: int, k: int = 3, cutoff_buckets: int = 1, exclude_self: bool = False, metric: str = "l2") -> DataFrame:
    """qid, rn, uid, d2: the best k of a query's bucket and `cutoff_buckets` on each side. points: uid, c0.., bucket (stashed); q: qid, c0..,
    bucket. Each query is sent to its few buckets and meets their points by an equi join: a bounded number of candidates a query."""
    return by_curves(points, q, dims, k, (cutoff_buckets,), exclude_self, metric).drop("cutoff")


def by_curves(points: DataFrame, q: DataFrame, dims: int, k: int, cutoffs: tuple[int, ...], exclude_self: bool = False, metric: str = "l2") -> DataFrame:
    """cutoff, qid, rn, uid, d2 for several cutoffs by one join: the best k of a bucket are found where it is, and count for each cutoff that reaches it."""
    c = max(cutoffs)
    near = q.withColumn("off", F.explode(F.sequence(F.lit(-c), F.lit(c)))).withColumn("bucket", F.col("bucket") + F.col("off")).withColumn("off", F.abs("off"))
    p = points.select("uid", "bucket", *[F.col(f"c{i}").alias(f"p{i}") for i in range(dims)])
    j = near.join(p, "bucket")
    if exclude_self:
        j = j.where("qid != uid")
    d2 = geometry.distance([F.col(f"c{i}") for i in range(dims)], [F.col(f"p{i}") for i in range(dims)], metric)
    first = W.partitionBy("bucket", "qid", "off").orderBy("d2", "uid")
    j = j.select("bucket", "off", "qid", "uid", d2.alias("d2")).withColumn("rn", F.row_number().over(first)).where(F.col("rn") <= k)
    j = j.withColumn("cutoff", F.explode(F.array(*[F.lit(x) for x in cutoffs]))).where("off <= cutoff")
    rn = F.row_number().over(W.partitionBy("cutoff", "qid").orderBy("d2", "uid"))
    return j.withColumn("rn", rn).where(F.col("rn") <= k).select("cutoff", "qid", "rn", "uid", F.round("d2", 12).alias("d2"))


def by_rank_window(points: DataFrame, q: DataFrame, dims: int, k: int, cutoff_points: int) -> DataFrame:
    """The cutoff as a number of points on each side along the curve: q has its rank; blocks of ranks make the window an equi join."""
    m = cutoff_points
    p = points.select("uid", "rank", F.expr(f"rank div {m}").alias("b"), *[F.col(f"c{i}").alias(f"p{i}") for i in range(dims)])
    near = q.withColumnRenamed("rank", "r").withColumn("b", F.explode(F.sequence(F.expr(f"r div {m}") - 1, F.expr(f"r div {m}") + 1)))
    j = near.join(p, "b").where(F.abs(F.col("rank") - F.col("r")) <= m)
    d2 = geometry.distance([F.col(f"c{i}") for i in range(dims)], [F.col(f"p{i}") for i in range(dims)])
    return _rank(j.withColumn("d2", d2).select("qid", "uid", "d2"), k)


def by_subtree(tree: kdtree.Tree, q: DataFrame, k: int, radius: float) -> DataFrame:
    """The best k within a radius of each query: cells whose box meets the ball are searched. Boxes of top cells are few, so a query finds its cells by a
    size-checked broadcast of them. The subtree is built in the cell's task, and its leaves are searched from the nearest on."""
    dims, cfg = tree.top.dims, tree.cfg

    def leaves(top: int, uid: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        b = kdtree.build_subtree(uid, c, cfg, top, kdtree.depth_of(top), cell=kdtree._cell(top, dims) if cfg.box == "cell" else None)
        order = np.argsort(b.path << (62 - b.depth.astype(np.int64)), kind="stable")  # leaves side by side stand together
        return order, np.flatnonzero(np.diff(b.path[order], prepend=-1))

    points = kdtree.assign_top(tree.points, tree.top).withColumnRenamed("top_id", "chunk")
    return _search(points, _counted(q, "qid", dims).withColumn("far", F.lit(radius * radius)), dims, k, False, leaves)


def exact(points: DataFrame, q: DataFrame, dims: int, k: int = 3, exclude_self: bool = False) -> DataFrame:
    """qid, rn, uid, d2: the k nearest of all points. Points are cut in chunks of the curve. A query's ball holds k points for certain (the farthest corner of
    the smallest cell around it that has so many), so only chunks whose box meets it are searched, and in them only blocks of points whose box does.
    Every bound adds in the order of the distance, so none of them can pass by a point that is near enough."""
    cols = [f"c{i}" for i in range(dims)]
    points, asked = points.select("uid", *cols), _counted(q, "qid", dims)
    box, n = geometry.bounding_box(points, dims), points.count()
    used = min(dims, 62)  # coordinates that a key has room for
    bits = min(20, 62 // used)
    key = lambda df: curves.keyed(df.select("*", *[F.least(F.greatest(F.col(c), F.lit(box[i][0])), F.lit(box[i][1])).alias(f"_{c}") for i, c in enumerate(cols)]).withColumnsRenamed({c: f"_in_{c}" for c in cols}).withColumnsRenamed({f"_{c}": c for c in cols}), used, bits, box=box).drop(*cols).withColumnsRenamed({f"_in_{c}": c for c in cols})  # noqa: E731  outside points get the key of the border
    if not n:
        return _rank(asked.limit(0).select("qid", F.col("qid").alias("uid"), F.lit(0.0).alias("d2"), "m"), k)
    keyed = key(points)
    chunks = _in_chunks(keyed, ranges(keyed, "key", ceil(n / CHUNK))).select("uid", *cols, "chunk")
    # rows that a cell needs: k besides those of one id, if that is not to be found
    need = k + (points.groupBy("uid").count().agg(F.max("count")).first()[0] if exclude_self else 0)
    low = max(0, used * bits - ceil(log2(max(2, n / CELL))))
    steps = -(-(used * bits - low) // 2) + 1
    edges = [(f, f"{a}{i}", c) for i, c in enumerate(cols) for a, f in (("lo", F.min), ("hi", F.max))]
    cells = keyed.groupBy(F.shiftright("key", low).alias("cell")).agg(F.count("*").alias("n"), *[f(c).alias(name) for f, name, c in edges])
    every = F.explode(F.sequence(F.lit(0), F.lit(steps)))
    up = F.expr("shiftright(cell, 2 * step)")
    cells = cells.withColumn("step", every).withColumn("cell", up).groupBy("step", "cell").agg(F.sum("n").alias("n"), *[f(name).alias(name) for f, name, _ in edges]).where(F.col("n") >= need)
    reach = _squares([F.greatest(F.abs(F.col(c) - F.col(f"lo{i}")), F.abs(F.col(c) - F.col(f"hi{i}"))) for i, c in enumerate(cols)])
    at = key(asked).withColumn("cell", F.shiftright("key", low)).withColumn("step", every).withColumn("cell", up)
    balls = at.join(cells, ["step", "cell"], "left").groupBy("qid", *cols, "m").agg(F.coalesce(F.min(reach), F.lit(inf)).alias("far"))

    def blocks(_: int, uid: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return np.argsort(_codes(c), kind="stable"), np.arange(0, len(c), BLOCK)

    return _search(chunks, tables.snapshot(balls, "balls"), dims, k, exclude_self, blocks)


def _counted(df: DataFrame, uid: str, dims: int) -> DataFrame:
    """Rows of one id and place become one, m counts them."""
    return df.groupBy(uid, *[F.col(f"c{i}") + F.lit(0.0) for i in range(dims)]).agg(F.count("*").alias("m")).toDF(uid, *[f"c{i}" for i in range(dims)], "m")


def _squares(xs: list):
    out = xs[0] * xs[0]
    for x in xs[1:]:  # the order of additions of the distance
        out = out + x * x
    return out


def _in_chunks(keyed: DataFrame, cuts: list) -> DataFrame:
    """Adds chunk, the number of cuts below the key: few by an expression, many by a search in an array."""
    if len(cuts) < CUTS:
        return keyed.withColumn("chunk", range_of(F.col("key"), cuts).cast("long"))
    tables.ship(keyed.sparkSession)
    ends = np.array([int(c) for c in cuts], np.int64)

    def run(batches):
        for x in batches:
            yield x.assign(chunk=np.searchsorted(ends, x["key"].to_numpy()))

    return keyed.mapInPandas(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in keyed.schema) + ", chunk long")


def _codes(c: np.ndarray) -> np.ndarray:
    """Morton codes of points on the grid of their own box."""
    c = c[:, :62]
    bits = min(16, 62 // c.shape[1])
    lo, width = c.min(0), np.ptp(c, 0)
    cell = np.minimum(((c - lo) / np.where(width > 0, width, 1.0) * (1 << bits)).astype(np.int64), (1 << bits) - 1)
    out = np.zeros(len(c), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(c.shape[1]):
            out = out << 1 | cell[:, i] >> b & 1
    return out


def _search(points: DataFrame, balls: DataFrame, dims: int, k: int, exclude_self: bool, order: Callable) -> DataFrame:
    """The best k of the points (uid, c0.., chunk) in each query's ball (qid, c0.., m, far: its squared radius). A chunk is searched in one task by the queries
    whose ball meets its box; equal rows go there as one with their number. `order` (chunk, uid, coordinates) gives the points' order and starts of blocks."""
    tables.ship(points.sparkSession)
    cols = [f"c{i}" for i in range(dims)]
    boxes = points.groupBy("chunk").agg(*[f(c).alias(f"{n}{i}") for i, c in enumerate(cols) for n, f in (("lo", F.min), ("hi", F.max))])
    boxes = tables.maybe_broadcast(tables.snapshot(boxes, "boxes"), 16 * dims + 8)
    gap = _squares([F.greatest(F.lit(0.0), F.col(f"lo{i}") - F.col(c), F.col(c) - F.col(f"hi{i}")) for i, c in enumerate(cols)])
    routed = balls.join(boxes, gap <= F.col("far")).select("qid", *cols, "m", "far", "chunk")
    # the table is dealt by chunk before rows are counted, so this is its only shuffle
    p = points.select("chunk", "uid", *cols).repartition("chunk").groupBy("chunk", "uid", *cols).agg(F.count("*").alias("m"))

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = [(np.zeros(0, np.int64),) * 2 + (np.zeros(0), np.zeros(0, np.int64))]
        if len(a) and len(b):
            uid, c, m = a["uid"].to_numpy(), a[cols].to_numpy(), a["m"].to_numpy()
            by, starts = order(int(a["chunk"].iloc[0]), uid, c)
            uid, c, m = uid[by], c[by], m[by]
            levels, need = _box_levels(c, starts), k + (int(np.unique(uid, return_counts=True)[1].max()) if exclude_self else 0)
            qid, qc, qm, far = b["qid"].to_numpy(), b[cols].to_numpy(), b["m"].to_numpy(), b["far"].to_numpy()
            for i in range(0, len(b), EXACT_QUERIES):
                s = slice(i, i + EXACT_QUERIES)
                qi, at, d2 = _nearest(uid, c, starts, levels, qid[s], qc[s], far[s].copy(), k, need, exclude_self)
                out.append((qid[s][qi], uid[at], d2, qm[s][qi] * m[at]))
        return pd.DataFrame(dict(zip(("qid", "uid", "d2", "m"), map(np.concatenate, zip(*out)))))

    found = p.groupBy("chunk").cogroup(routed.groupBy("chunk")).applyInPandas(run, "qid long, uid long, d2 double, m long")
    w = W.partitionBy("qid").orderBy("d2", "uid").rowsBetween(W.unboundedPreceding, -1)
    found = found.withColumn("_b", F.coalesce(F.sum("m").over(w), F.lit(0))).where(F.col("_b") < k)
    return found.withColumn("rn", F.explode(F.sequence(F.col("_b") + 1, F.least(F.col("_b") + F.col("m"), F.lit(k))))).select("qid", F.col("rn").cast("int").alias("rn"), "uid", F.round("d2", 12).alias("d2"))


def _box_levels(c: np.ndarray, starts: np.ndarray) -> list[tuple]:
    """Boxes and numbers of points of blocks, of FAN blocks each, and so on up."""
    out = [(np.minimum.reduceat(c, starts, 0), np.maximum.reduceat(c, starts, 0), np.diff(starts, append=len(c)))]
    while len(out[-1][2]) > FAN:
        lo, hi, n = out[-1]
        s = np.arange(0, len(n), FAN)
        out.append((np.minimum.reduceat(lo, s, 0), np.maximum.reduceat(hi, s, 0), np.add.reduceat(n, s)))
    return out


def _sum_squares(x: np.ndarray) -> np.ndarray:
    out = x[:, 0] * x[:, 0]
    for t in range(1, x.shape[1]):  # the same order of additions as the expression
        out = out + x[:, t] * x[:, t]
    return out


#: Distances that a task computes at once.
DISTANCES = 1 << 20


def _nearest(uid: np.ndarray, c: np.ndarray, starts: np.ndarray, levels: list[tuple], qid: np.ndarray, qc: np.ndarray, far: np.ndarray, k: int, need: int, exclude_self: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Query, point and squared distance of the best k in each query's ball. All queries go down the boxes together; balls shrink to the farthest corner of
    a box that holds enough points, then to the k-th distance in the block of the nearest such corner."""
    qi, node = np.repeat(np.arange(len(qc)), len(levels[-1][2])), np.tile(np.arange(len(levels[-1][2])), len(qc))
    for depth in range(len(levels) - 1, -1, -1):
        lo, hi, n = levels[depth]
        q = qc[qi]
        low, high = lo[node] - q, q - hi[node]
        gap, corner = _sum_squares(np.maximum(np.maximum(low, high), 0.0)), _sum_squares(np.maximum(np.abs(low), np.abs(high)))
        enough = n[node] >= need
        np.minimum.at(far, qi[enough], corner[enough])
        keep = gap <= far[qi]
        qi, node, gap, corner = qi[keep], node[keep], gap[keep], corner[keep]
        if depth:
            node = (node[:, None] * FAN + np.arange(FAN)).ravel()
            there = node < len(levels[depth - 1][2])
            qi, node = np.repeat(qi, FAN)[there], node[there]
    size = levels[0][2]

    def measured(qi: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n = size[node]
        at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n - starts[node], n)
        qi = np.repeat(qi, n)
        d2 = _sum_squares(qc[qi] - c[at])
        keep = d2 <= far[qi]
        if exclude_self:
            keep &= uid[at] != qid[qi]
        return _best(qi[keep], at[keep], d2[keep], uid, k)

    by = np.lexsort((corner, qi))
    first = by[np.flatnonzero(np.diff(qi[by], prepend=-1))]
    found = [measured(qi[first], node[first])]
    q, _, d2 = found[0]
    last = np.flatnonzero(np.diff(q, append=-1))
    last = last[(last >= k - 1) & (q[np.maximum(last - k + 1, 0)] == q[last])]  # queries with k points
    far[q[last]] = np.minimum(far[q[last]], d2[last])
    rest = gap <= far[qi]
    rest[first] = False
    qi, node = qi[rest], node[rest]
    ends = np.cumsum(size[node])
    cut = np.searchsorted(ends, np.arange(DISTANCES, ends[-1] + 1, DISTANCES)) if len(ends) else []
    found += [measured(a, b) for a, b in zip(np.split(qi, cut), np.split(node, cut)) if len(a)]
    return _best(*map(np.concatenate, zip(*found)), uid, k)


def _best(qi: np.ndarray, at: np.ndarray, d2: np.ndarray, uid: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    by = np.lexsort((uid[at], d2, qi))
    q = qi[by]
    new = np.diff(q, prepend=-1) != 0
    start = np.flatnonzero(new)
    by = by[np.arange(len(q)) - start[np.cumsum(new) - 1] < k] if len(q) else by
    return qi[by], at[by], d2[by]
