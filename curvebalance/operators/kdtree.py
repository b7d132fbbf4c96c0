"""Binary space trees: distributed top cells, local subtrees, node tables and tree curve keys.

A node is a path: the root is 1, children of p are 2p (x <= m) and 2p + 1. Points are uid, c0.., w, scaled to the unit box of the whole set.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from curvebalance.functions import geometry
from curvebalance.plans import tables
from curvebalance.plans.specs import TreeConfig

HASH_A, HASH_M, HASH_P = 2654435761, 1 << 32, 2147483647


def hash_unit(uid: Column) -> Column:
    """An arithmetic hash in [0, 2**32) that SQL engines agree on."""
    return F.pmod(F.pmod(uid, F.lit(HASH_P)) * F.lit(HASH_A), F.lit(HASH_M))


def in_sample(uid: Column, frac: float) -> Column:
    return hash_unit(uid) < F.lit(int(frac * HASH_M))


def _hash_np(uid: np.ndarray) -> np.ndarray:
    return uid % HASH_P * HASH_A % HASH_M


# ---- local subtrees ----


def split_value(x: np.ndarray, uid: np.ndarray, splitter: str, frac: float) -> float:
    """Where a set of values is cut: lower values and the value itself go down. A median equal to the maximum gives way to the midpoint."""
    lo, hi = x.min(), x.max()
    mid = (lo + hi) / 2
    if splitter == "midpoint":
        return mid
    if splitter != "median_sort":
        x = x[_hash_np(uid) < int(frac * HASH_M)]
        if not len(x):
            return mid
    k = (len(x) + 1) // 2 - 1
    m = np.sort(x)[k] if splitter in ("median_sort", "median_sample_sort") else np.partition(x, k)[k]
    return mid if m >= hi else float(m)


@dataclass
class Built:
    """Leaves of a subtree: each point's path and depth; and its nodes, if asked for."""

    path: np.ndarray
    depth: np.ndarray
    nodes: list[tuple] = field(default_factory=list)


def build_subtree(uid: np.ndarray, c: np.ndarray, cfg: TreeConfig, path: int = 1, depth: int = 0, w: np.ndarray | None = None, cell=None, want_nodes: bool = False, stop: int | None = None) -> Built:
    """Splits points (n, d) below a node until buckets hold `bucket_size`. An explicit stack, so depth is no limit."""
    n, d = c.shape
    out = Built(np.full(n, path, np.int64), np.full(n, depth, np.int32))
    stack = [(np.arange(n), path, depth, cell if cell is not None else [(0.0, 1.0)] * d)]
    while stack:
        at, p, k, box = stack.pop()
        x = c[at]
        lo, hi = (x.min(0), x.max(0)) if len(at) else (np.zeros(d), np.zeros(d))
        width = hi - lo
        leaf = len(at) <= cfg.bucket_size or not (width > 0).any() or k >= (cfg.max_depth if stop is None else min(stop, cfg.max_depth))
        dim, m = -1, 0.0
        if not leaf:
            if cfg.dim_rule == "widest":
                dim = int(width.argmax())
            else:
                dim = k % d
            if cfg.box == "cell":
                m = (box[dim][0] + box[dim][1]) / 2
            elif width[dim] > 0:
                m = split_value(x[:, dim], uid[at], cfg.splitter(k), cfg.sample_frac)
            else:
                m = float(lo[dim])
        if want_nodes:
            out.nodes.append((p, k, dim, m, leaf, len(at), int(w[at].sum()) if w is not None else len(at), lo.tolist(), hi.tolist()))
        if leaf:
            out.path[at], out.depth[at] = p, k
            continue
        down = x[:, dim] <= m if cfg.box == "tight" else x[:, dim] < m
        low, high = list(box), list(box)
        low[dim], high[dim] = (box[dim][0], m), (m, box[dim][1])
        stack.append((at[~down], 2 * p + 1, k + 1, high))
        stack.append((at[down], 2 * p, k + 1, low))
    return out


# ---- top tree ----


@dataclass
class TopTree:
    """Inner nodes (path -> (dim, value)) and leaves (path -> (points, weight)) of the distributed part; small, on the driver."""

    dims: int
    inner: dict[int, tuple[int, float]]
    cells: dict[int, tuple[int, int]]

    def cell_of(self, coords: list[Column]) -> Column:
        """The top cell of a point as nested comparisons: compiled, no shuffle, no Python."""

        def node(p: int) -> Column:
            if p not in self.inner:
                return F.lit(p).cast("long")
            dim, m = self.inner[p]
            return F.when(coords[dim] <= F.lit(m), node(2 * p)).otherwise(node(2 * p + 1))

        return node(1)

    def assign_np(self, c: np.ndarray) -> np.ndarray:
        """The same for arrays, level by level; for trees too large for one expression."""
        paths = sorted(self.inner)
        at = np.full(len(c), 1, np.int64)
        keys = np.array(paths, np.int64)
        dim = np.array([self.inner[p][0] for p in paths], np.int64)
        val = np.array([self.inner[p][1] for p in paths])
        live = np.arange(len(c))
        while len(live) and len(keys):
            i = np.searchsorted(keys, at[live])
            ok = (i < len(keys)) & (keys[np.minimum(i, len(keys) - 1)] == at[live])
            live, i = live[ok], i[ok]
            at[live] = 2 * at[live] + (c[live, dim[i]] > val[i])
        return at


def depth_of(path: int) -> int:
    return path.bit_length() - 1


#: Cells that an assignment by nested comparisons may have.
EXPRESSION_CELLS = 256


def assign_top(points: DataFrame, top: TopTree) -> DataFrame:
    """Adds top_id. Few cells: an expression. Many: Arrow batches through the tree's arrays."""
    if len(top.cells) <= EXPRESSION_CELLS:
        return points.withColumn("top_id", top.cell_of([F.col(f"c{i}") for i in range(top.dims)]))
    tables.ship(points.sparkSession)
    cols = [f"c{i}" for i in range(top.dims)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in batches:
            yield x.assign(top_id=top.assign_np(x[cols].to_numpy()))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema)
    return points.mapInPandas(run, schema + ", top_id long")


def node_medians(points: DataFrame, top: TopTree, wanted: dict[int, tuple[int, int, float, float]], bins: int = 256, rounds: int = 3) -> dict[int, float]:
    """Exact order statistics of many nodes at once, by histograms that zoom in: path -> (dim, rank from 1, lo, hi) gives path -> value.

    Each round is one aggregate of at most nodes * bins rows. What is left after the last is counted by value.
    """
    spark = points.sparkSession
    dim = F.element_at(F.array(*[f"c{i}" for i in range(top.dims)]), F.col("_d") + 1)
    df = assign_top(points, top).withColumnRenamed("top_id", "_p")
    want = spark.createDataFrame([(int(p), int(v[0])) for p, v in wanted.items()], "_p long, _d int")
    df = df.join(F.broadcast(want), "_p").select("_p", dim.alias("x"))  # a row a node
    left = {p: v[1] for p, v in wanted.items()}
    span = {p: (v[2], v[3]) for p, v in wanted.items()}
    for _ in range(rounds):
        t = spark.createDataFrame([(int(p), float(a), float(b)) for p, (a, b) in span.items()], "_p long, _a double, _z double")
        width = F.col("_z") - F.col("_a")
        b = F.when(width > 0, F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((F.col("x") - F.col("_a")) / width * bins)))).otherwise(0).cast("int")
        df = df.join(F.broadcast(t), "_p").select("_p", "x", b.alias("b"))
        rows = df.groupBy("_p", "b").agg(F.count("*").alias("n"), F.min("x").alias("lo"), F.max("x").alias("hi")).collect()
        pick: dict[int, int] = {}
        for p in wanted:
            for r in sorted((r for r in rows if r["_p"] == p), key=lambda r: r["b"]):
                if left[p] <= r["n"]:
                    pick[p], span[p] = r["b"], (r["lo"], r["hi"])
                    break
                left[p] -= r["n"]
        df = df.join(F.broadcast(spark.createDataFrame([(int(p), int(v)) for p, v in pick.items()], "_p long, b int")), ["_p", "b"]).select("_p", "x")
        if all(a == b for a, b in span.values()):
            break
    out = {p: a for p, (a, b) in span.items() if a == b}
    if len(out) < len(wanted):
        # few values a node are left after three rounds of 256 bins; a running count over them finds the rank
        ranks = spark.createDataFrame([(int(p), int(v)) for p, v in left.items()], "_p long, _k long")
        run = F.sum("n").over(W.partitionBy("_p").orderBy("x"))
        rows = df.groupBy("_p", "x").agg(F.count("*").alias("n")).withColumn("r", run).join(F.broadcast(ranks), "_p").where("r >= _k").groupBy("_p").agg(F.min("x").alias("x")).collect()
        out |= {r["_p"]: r["x"] for r in rows if r["_p"] not in out}
    return out


def build_top(points: DataFrame, dims: int, cfg: TreeConfig, bits: int = 5) -> TopTree:
    """Splits until there are k1 cells or all hold at most a bucket.

    exact: one aggregate a level, the same splits as the whole tree's. histogram: one scan counts a grid of 2**bits cells a dimension, and the
    driver splits the counts. sample: one scan, the driver splits a hashed sample.
    """
    if cfg.top_mode == "exact":
        return _top_exact(points, dims, cfg)
    if cfg.top_mode == "histogram":
        cells = [geometry.quantised(F.col(f"c{i}"), 0.0, 1.0, bits) for i in range(dims)]
        rows = points.groupBy(*[c.alias(f"g{i}") for i, c in enumerate(cells)]).agg(F.count("*").alias("n"), F.sum("w").alias("w")).collect()
        c = (np.array([[r[f"g{i}"] for i in range(dims)] for r in rows], float).reshape(-1, dims) + 0.5) / (1 << bits)
        n, w = np.array([r["n"] for r in rows], np.int64), np.array([r["w"] for r in rows], np.int64)
        grid = 1 << bits
    else:
        rows = points.where(in_sample(F.col("uid"), cfg.sample_frac)).select(*[f"c{i}" for i in range(dims)], "w").collect()
        c = np.array([r[:-1] for r in rows], float).reshape(-1, dims)
        each = max(1, round(1 / cfg.sample_frac))  # points a sampled one stands for, so that cells too large for a task are seen
        n, w, grid = np.full(len(rows), each, np.int64), np.array([r[-1] for r in rows], np.int64) * each, 0
    inner: dict[int, tuple[int, float]] = {}
    live = {1: np.arange(len(n))}
    while len(live) < cfg.k1:
        p = max(live, key=lambda q: (int(n[live[q]].sum()), -q))
        at = live[p]
        width = c[at].max(0) - c[at].min(0) if len(at) else np.zeros(dims)
        if not (width > 0).any() or depth_of(p) >= 30:
            break
        dim = int(width.argmax())
        x = c[at, dim]
        if cfg.splitter(depth_of(p)) == "midpoint":
            m = (x.min() + x.max()) / 2
        else:
            order = np.argsort(x, kind="stable")
            m = x[order][np.searchsorted(np.cumsum(n[at][order]), (n[at].sum() + 1) // 2)]
        if grid:  # cut between grid cells
            m = np.floor(m * grid) / grid if np.floor(m * grid) / grid > x.min() else np.ceil(m * grid) / grid
        if m >= x.max():
            m = (x.min() + x.max()) / 2
        inner[p] = (dim, float(m))
        del live[p]
        live[2 * p], live[2 * p + 1] = at[x <= m], at[x > m]
    return TopTree(dims, inner, {p: (int(n[a].sum()), int(w[a].sum())) for p, a in live.items()})


def _top_exact(points: DataFrame, dims: int, cfg: TreeConfig) -> TopTree:
    top = TopTree(dims, {}, {})
    coords = [F.col(f"c{i}") for i in range(dims)]
    done: dict[int, tuple[int, int]] = {}
    live: dict[int, list[tuple[float, float]]] = {1: [(0.0, 1.0)] * dims}
    depth = 0
    while live and len(live) + len(done) < cfg.k1:
        aggs = [F.count("*").alias("n"), F.sum("w").alias("w"), *[f(f"c{i}").alias(f"{k}{i}") for i in range(dims) for k, f in (("lo", F.min), ("hi", F.max))]]
        split = cfg.splitter(depth)
        sampled = split in ("median_sample_sort", "median_sample_select")
        if sampled:
            aggs += [F.sum(in_sample(F.col("uid"), cfg.sample_frac).cast("long")).alias("s")]
        rows = points.withColumn("_p", top.cell_of(coords)).where(F.col("_p").isin([int(p) for p in live])).groupBy("_p").agg(*aggs).collect()
        plan: dict[int, tuple[int, float]] = {}
        wanted: dict[int, tuple[int, int, float, float]] = {}
        for r in rows:
            p, width = r["_p"], [r[f"hi{i}"] - r[f"lo{i}"] for i in range(dims)]
            if r["n"] <= cfg.bucket_size or max(width) <= 0 or depth >= cfg.max_depth:
                done[p] = (r["n"], r["w"])
                continue
            dim = width.index(max(width)) if cfg.dim_rule == "widest" else depth % dims
            lo, hi = r[f"lo{dim}"], r[f"hi{dim}"]
            plan[p] = (dim, (live[p][dim][0] + live[p][dim][1]) / 2 if cfg.box == "cell" else (lo + hi) / 2)
            count = r["s"] if sampled else r["n"]
            if split != "midpoint" and count:
                wanted[p] = (dim, (count + 1) // 2, lo, hi)
        if wanted:
            base = points.where(in_sample(F.col("uid"), cfg.sample_frac)) if sampled else points
            for p, m in node_medians(base, top, wanted).items():
                if m < wanted[p][3]:
                    plan[p] = (wanted[p][0], m)
        nxt = {}
        for p, (dim, m) in plan.items():
            top.inner[p] = (dim, m)
            for side in (0, 1):
                box = list(live[p])
                box[dim] = (box[dim][0], m) if side == 0 else (m, box[dim][1])
                nxt[2 * p + side] = box
        live = nxt
        depth += 1
    if live:
        for r in points.withColumn("_p", top.cell_of(coords)).where(F.col("_p").isin([int(p) for p in live])).groupBy("_p").agg(F.count("*").alias("n"), F.sum("w").alias("w")).collect():
            done[r["_p"]] = (r["n"], r["w"])
    top.cells = done
    return top


# ---- whole trees ----


@dataclass
class Tree:
    top: TopTree
    cfg: TreeConfig
    points: DataFrame
    members: DataFrame

    def nodes(self) -> DataFrame:
        return node_table(self)


#: Points a task builds a subtree from; larger top cells are split further by a second level.
CELL_POINTS = 2_000_000


def build(points: DataFrame, dims: int, cfg: TreeConfig) -> Tree:
    """members: uid, coordinates, w, top_id, path, depth. Top cells by expressions, then one shuffle that brings each cell's points together, then
    arrays. A cell with too many points for a task is cut into k2 second-level cells first."""
    tables.ship(points.sparkSession)
    top = build_top(points, dims, cfg)
    big = [p for p, (n, _) in top.cells.items() if n > CELL_POINTS]
    while big:
        before = len(top.cells)
        sub = TreeConfig(**{**cfg.__dict__, "k1": before + cfg.k2 * len(big)})
        top = build_top(points, dims, sub)
        big = [p for p, (n, _) in top.cells.items() if n > CELL_POINTS] if len(top.cells) > before else []
    return Tree(top, cfg, points, build_local(assign_top(points, top), dims, cfg))


def build_local(assigned: DataFrame, dims: int, cfg: TreeConfig) -> DataFrame:
    cols = [f"c{i}" for i in range(dims)]

    def run(g: pd.DataFrame) -> pd.DataFrame:
        p = int(g["top_id"].iloc[0])
        b = build_subtree(g["uid"].to_numpy(), g[cols].to_numpy(), cfg, p, depth_of(p), cell=_cell(p, dims) if cfg.box == "cell" else None)
        return g.assign(path=b.path, depth=b.depth)

    schema = "uid long, " + ", ".join(f"{c} double" for c in cols) + ", w long, top_id long, path long, depth int"
    return assigned.select("uid", *cols, "w", "top_id").groupBy("top_id").applyInPandas(run, schema)


def split_planes(members: DataFrame, dims: int, cfg: TreeConfig, by: str = "top_id") -> DataFrame:
    """by, path, dim, value of every inner node below the top cells (or other roots, named by `by`): the splits that `build_local` makes, which it
    need not keep. Members: uid, c0.., and the root."""
    cols = [f"c{i}" for i in range(dims)]
    tables.ship(members.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        p = int(g[by].iloc[0])
        b = build_subtree(g["uid"].to_numpy(), g[cols].to_numpy(), cfg, p, depth_of(p), want_nodes=True, cell=_cell(p, dims) if cfg.box == "cell" else None)
        rows = [(p, int(q), int(d), float(m)) for q, _, d, m, leaf, *_ in b.nodes if not leaf]
        return pd.DataFrame(rows, columns=[by, "path", "dim", "value"]).astype({by: "int64", "path": "int64", "dim": "int32", "value": "float64"})

    return members.select(by, "uid", *cols).groupBy(by).applyInPandas(run, f"{by} long, path long, dim int, value double")


def _cell(path: int, dims: int) -> list[tuple[float, float]]:
    """The cell of a path in a cyclic-midpoint tree over the unit box."""
    box = [(0.0, 1.0)] * dims
    for k, bit in enumerate(f"{path:b}"[1:]):
        lo, hi = box[k % dims]
        box[k % dims] = (lo, (lo + hi) / 2) if bit == "0" else ((lo + hi) / 2, hi)
    return box


def build_levels(points: DataFrame, dims: int, cfg: TreeConfig, levels: int | None = None) -> DataFrame:
    """The same tree level by level with DataFrame operations only: uid, path, depth. Each level is one aggregate by node and a join with its
    few columns; lineage is cut every level. For midpoint and exact medians."""
    cols = [f"c{i}" for i in range(dims)]
    live = points.select("uid", *cols, F.lit(1).cast("long").alias("path"))
    done, depth = [], 0
    limit = cfg.max_depth if levels is None else min(levels, cfg.max_depth)
    while True:
        box = live.groupBy("path").agg(F.count("*").alias("n"), *[f(c).alias(f"{k}_{c}") for c in cols for k, f in (("lo", F.min), ("hi", F.max))])
        width = [F.col(f"hi_{c}") - F.col(f"lo_{c}") for c in cols]
        top = F.greatest(*width) if dims > 1 else width[0]
        pick = lambda make: F.coalesce(*[F.when(w == top, make(c)) for w, c in zip(width, cols)])  # noqa: E731  the first of equal widths
        box = box.withColumn("split", (F.col("n") > cfg.bucket_size) & (top > 0) & F.lit(depth < limit)).withColumn("dim", pick(lambda c: F.lit(cols.index(c))))
        box = box.withColumn("lo", pick(lambda c: F.col(f"lo_{c}"))).withColumn("hi", pick(lambda c: F.col(f"hi_{c}"))).select("path", "n", "split", "dim", "lo", "hi")
        j = live.join(tables.maybe_broadcast(tables.snapshot(box, "level"), 60), "path")
        done.append(j.where("not split").select("uid", "path", F.lit(depth).alias("depth")))
        j = j.where("split").withColumn("x", F.element_at(F.array(*cols), F.col("dim") + 1))
        mid = (F.col("lo") + F.col("hi")) / 2
        if cfg.splitter(depth) == "midpoint":
            m = mid
        else:
            rn = F.row_number().over(W.partitionBy("path").orderBy("x", "uid"))
            j = j.withColumn("rn", rn)
            med = F.max(F.when(F.col("rn") == F.floor((F.col("n") + 1) / 2), F.col("x"))).over(W.partitionBy("path"))
            m = F.when(med >= F.col("hi"), mid).otherwise(med)
        j = j.withColumn("m", m).select("uid", *cols, (F.col("path") * 2 + (F.col("x") > F.col("m")).cast("long")).alias("path"))
        live = tables.snapshot(j, "points")
        depth += 1
        if live.isEmpty():
            break
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def node_table(tree: Tree) -> DataFrame:
    """Every node: path, depth, parent, split_dim, split_val, is_leaf, n, w and tight box, from the leaves upwards by aggregates."""
    dims = tree.top.dims
    cols = [f"c{i}" for i in range(dims)]
    m = tree.members
    leaves = m.groupBy("path", "depth").agg(F.count("*").alias("n"), F.sum("w").alias("w"), *[f(c).alias(f"{k}{i}") for i, c in enumerate(cols) for k, f in (("lo", F.min), ("hi", F.max))])
    up = roll_up(leaves, {"n": F.sum, "w": F.sum, **{f"lo{i}": F.min for i in range(dims)}, **{f"hi{i}": F.max for i in range(dims)}})
    is_leaf = leaves.select(F.col("path").alias("leaf"))
    up = up.join(is_leaf, up["path"] == is_leaf["leaf"], "left").withColumn("is_leaf", F.col("leaf").isNotNull()).drop("leaf")
    planes = split_planes(m, dims, tree.cfg).select("path", F.col("dim").alias("split_dim"), F.col("value").alias("split_val"))
    if tree.top.inner:
        planes = planes.unionByName(m.sparkSession.createDataFrame([(int(p), int(d), float(v)) for p, (d, v) in tree.top.inner.items()], planes.schema))
    up = up.join(planes, "path", "left")
    return up.withColumn("parent", F.shiftright("path", 1)).withColumn("box", F.array(*[F.struct(F.col(f"lo{i}").alias("lo"), F.col(f"hi{i}").alias("hi")) for i in range(dims)])).select("path", "depth", "parent", "split_dim", "split_val", "is_leaf", "n", "w", "box")


def roll_up(leaves: DataFrame, how: dict[str, Callable]) -> DataFrame:
    """Aggregates of leaves at all their ancestors: each leaf is expanded to its path's prefixes, then one partial and final aggregate."""
    up = leaves.withColumn("_k", F.explode(F.sequence(F.lit(0), F.col("depth")))).withColumn("path", F.expr("shiftright(path, _k)")).withColumn("depth", F.col("depth") - F.col("_k"))
    return up.groupBy("path", "depth").agg(*[f(c).alias(c) for c, f in how.items()])


# ---- curves on trees ----


def leaf_key(path: Column, depth: Column) -> Column:
    """Morton order of the leaves of one tree: the path's bits below the root, left-aligned in 62."""
    return F.expr(f"shiftleft({_name(path)} - shiftleft(1L, {_name(depth)}), 62 - {_name(depth)})")


def _name(c: Column) -> str:
    return c._jc.toString()


def hilbert_walk(nodes: dict[int, int], dims: int, variant: str = "full", start: tuple[int, int] = (0, 0)) -> list[tuple[int, int, int]]:
    """Leaf paths in Hilbert-like order, each with the state it is entered in, from inner nodes (path -> split dimension).

    State: entry corner e and axis a. If below a node every dimension is split exactly once on every path, the 2**d descendants are visited in
    the Gray-code order that starts at e and flips a last, each with the published next state; otherwise the node's two
    children are visited from the side of e. `pairs` does the first on two dimensions at a time.
    """
    group = dims if variant == "full" else min(2, dims)
    out: list[tuple[int, int, int]] = []
    stack: list[tuple[int, int, int]] = [(1, *start)]

    def block(p: int) -> dict[int, int] | None:
        """Corner -> descendant, if a full block of `group` dimensions stands below p."""
        want: set[int] | None = None if group < dims else set(range(dims))
        found: dict[int, int] = {}
        todo = [(p, 0, frozenset())]
        sets = set()
        while todo:
            q, corner, used = todo.pop()
            if len(used) == group:
                found[corner] = q
                sets.add(used)
                continue
            k = nodes.get(q)
            if k is None or k in used or (want is not None and k not in want):
                return None
            todo.append((2 * q, corner, used | {k}))
            todo.append((2 * q + 1, corner | 1 << k, used | {k}))
        return found if len(sets) == 1 else None

    while stack:
        p, e, a = stack.pop()
        if p not in nodes:
            out.append((p, e, a))
            continue
        b = block(p)
        if b is None:
            k = nodes[p]
            first = e >> k & 1
            stack.append((2 * p + 1 - first, e, a))
            stack.append((2 * p + first, e, k))
            continue
        dims_in = sorted({k for c in b for k in range(dims) if any(c >> k & 1 != o >> k & 1 for o in b)})
        g = len(dims_in)
        axis = dims_in.index(a) if a in dims_in else 0
        entry = sum((e >> k & 1) << i for i, k in enumerate(dims_in))
        todo = []
        for w in range(1 << g):
            corner = _rotl(w ^ w >> 1, axis + 1, g) ^ entry
            full = sum((corner >> i & 1) << k for i, k in enumerate(dims_in))
            ne = _rotl(_entry(w), axis + 1, g) ^ entry
            na = (axis + _axis(w, g) + 1) % g
            keep = e & ~sum(1 << k for k in dims_in)
            todo.append((b[full], keep | sum((ne >> i & 1) << k for i, k in enumerate(dims_in)), dims_in[na]))
        stack.extend(reversed(todo))
    return out


def _rotl(x: int, k: int, n: int) -> int:
    k %= n
    return (x << k | x >> n - k) & (1 << n) - 1


def _entry(w: int) -> int:
    """Entry corner of the w-th cell of a block (published rule)."""
    if w == 0:
        return 0
    v = 2 * ((w - 1) // 2)
    return v ^ v >> 1


def _axis(w: int, n: int) -> int:
    """Axis of the w-th cell of a block (published rule): trailing ones of a neighbour's number."""
    if w == 0:
        return 0
    v = w - 1 if w % 2 == 0 else w
    return ((v + 1 & -(v + 1)).bit_length() - 1) % n


def tree_order(tree: Tree, curve: str = "morton", variant: str = "full") -> DataFrame:
    """members with key: their leaf's place along the curve. Morton keys are path arithmetic. Hilbert-like places need the visiting state, so
    the node table is walked on the driver when it is a top tree's size, and cell by cell otherwise."""
    m = tree.members
    if curve == "morton":
        return m.withColumn("key", leaf_key(F.col("path"), F.col("depth")))
    # the top tree is walked on the driver; each subtree goes on in its task from the state in which its cell is entered
    rank = {p: (i, e, a) for i, (p, e, a) in enumerate(hilbert_walk({p: d for p, (d, _) in tree.top.inner.items()}, tree.top.dims, variant))}
    dims, cfg = tree.top.dims, tree.cfg
    cols = [f"c{i}" for i in range(dims)]

    def run(g: pd.DataFrame) -> pd.DataFrame:
        p = int(g["top_id"].iloc[0])
        b = build_subtree(g["uid"].to_numpy(), g[cols].to_numpy(), cfg, p, depth_of(p), cell=_cell(p, dims) if cfg.box == "cell" else None, want_nodes=True)
        inner = {_below(q, p): dim for q, _, dim, _, leaf, *_ in b.nodes if not leaf}
        i, *state = rank[p]
        place = {q: k for k, (q, _, _) in enumerate(hilbert_walk(inner, dims, variant, tuple(state)))}
        key = np.array([i << 40 | place[_below(int(q), p)] for q in b.path], np.int64)
        return g.assign(path=b.path, depth=b.depth, key=key)

    schema = "uid long, " + ", ".join(f"{c} double" for c in cols) + ", w long, top_id long, path long, depth int, key long"
    return m.select("uid", *cols, "w", "top_id").groupBy("top_id").applyInPandas(run, schema)


def _below(path: int, top: int) -> int:
    """A path relative to a node above it."""
    k = depth_of(path) - depth_of(top)
    return 1 << k | path & (1 << k) - 1
