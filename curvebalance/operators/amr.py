"""An adaptive mesh around a moving ball: refined blocks, a stencil, and balancing policies."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from curvebalance.functions import curves
from curvebalance.plans import tables
from curvebalance.plans.prefix import range_of, with_prefix

from . import amortise, slicing


def ball_centre(step: int, steps: int) -> float:
    """The ball's centre on the diagonal of the unit cube, corner to corner."""
    return step / (steps - 1) if steps > 1 else 0.0


def moving_ball(points: DataFrame, dims: int, centre: float, radius: float, levels: int = 1, growth: int = 8) -> DataFrame:
    """Points (unit cube) with the weight of their block: growth**level, the level by how many radii (r, r/2, ...) of the ball they are within."""
    d2 = sum(((F.col(f"c{i}") - F.lit(centre)) * (F.col(f"c{i}") - F.lit(centre)) for i in range(1, dims)), (F.col("c0") - F.lit(centre)) * (F.col("c0") - F.lit(centre)))
    w: Column = F.lit(1).cast("long")
    for k in range(1, levels + 1):
        r = radius / (1 << k - 1)
        w = F.when(d2 <= F.lit(r * r), F.lit(growth**k).cast("long")).otherwise(w)
    return points.withColumn("w", w)


def stencil(blocks: DataFrame, dims: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """uid, g0.., v and the columns to keep: the mean of a block (g0.., v) and its face neighbours. The value is sent to the 2d neighbours and itself, then
    one aggregate: no join, one shuffle."""
    offsets = [tuple(0 for _ in range(dims))] + [tuple(s if k == i else 0 for k in range(dims)) for i in range(dims) for s in (-1, 1)]
    sent = blocks.select("v", F.explode(F.array(*[F.struct(*[(F.col(f"g{k}") + o[k]).alias(f"g{k}") for k in range(dims)], F.lit(not any(o)).alias("own"), *[F.col(c) if not any(o) else F.lit(None).cast(blocks.schema[c].dataType).alias(c) for c in ("uid", *keep)]) for o in offsets])).alias("t"))
    g = sent.groupBy(*[F.col(f"t.g{k}").alias(f"g{k}") for k in range(dims)]).agg(*[F.max(f"t.{c}").alias(c) for c in ("uid", *keep)], F.avg("v").alias("v"), F.max(F.col("t.own").cast("int")).alias("own"))
    return g.where("own = 1").select("uid", *[f"g{k}" for k in range(dims)], "v", *keep)


def adapt(blocks: DataFrame, dims: int, side: int, centre: float, radius: float) -> DataFrame:
    """Blocks (uid, level, g0.., v, part) of a mesh of side**dims, of which those whose own centre is in the ball have 2**dims children: coarse blocks
    that it has reached are split (children take value and part), and children that it has left become their block again (the mean, the least part)."""
    one = 1 << dims
    mid = [(F.floor(F.col(f"g{i}") / F.when(F.col("level") == 0, 1).otherwise(2)) + 0.5) / side - F.lit(centre) for i in range(dims)]
    b = blocks.withColumn("inside", sum((m * m for m in mid[1:]), mid[0] * mid[0]) <= F.lit(radius * radius))
    stay = b.where((F.col("level") == 1) == F.col("inside")).drop("inside")
    cols = blocks.columns
    split = b.where((F.col("level") == 0) & F.col("inside")).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(one - 1))))
    split = split.select((F.col("uid") * one + F.col("k") + side**dims).alias("uid"), F.lit(1).alias("level"), *[(F.col(f"g{i}") * 2 + F.shiftright("k", dims - 1 - i).bitwiseAND(F.lit(1))).cast("long").alias(f"g{i}") for i in range(dims)], "v", "part").select(*cols)
    left = b.where((F.col("level") == 1) & ~F.col("inside")).withColumn("uid", F.floor((F.col("uid") - side**dims) / one).cast("long"))
    joined = left.groupBy("uid").agg(F.lit(0).alias("level"), *[F.floor(F.min(f"g{i}") / 2).cast("long").alias(f"g{i}") for i in range(dims)], F.avg("v").alias("v"), F.min("part").alias("part")).select(*cols)
    return stay.unionByName(split).unionByName(joined)


def mesh_run(mesh: DataFrame, dims: int, side: int, parts: int, steps: int, radius: float, policy: str = "amortised", balance_cost: float = 0.5, clock: str = "model") -> tuple[DataFrame, list[dict]]:
    """The whole loop on a mesh (uid, g0.., v): blocks are refined and coarsened as the ball crosses, the stencil runs over the neighbours of equal level, and
    the blocks are cut again when the policy says so. Returns the last blocks and a row a step: blocks, refined ones, heaviest load over the mean, rebalances
    and seconds of refinement, stencil and balancing."""
    bits, far = max(1, (2 * side - 1).bit_length()), 4 * side  # levels lie apart, so a stencil does not mix them

    def cut(b: DataFrame) -> DataFrame:
        corner = [F.col(f"g{i}") * F.when(F.col("level") == 0, 2).otherwise(1) for i in range(dims)]
        keyed = tables.snapshot(b.withColumn("key", curves.interleave(corner, bits)).withColumn("w", F.lit(1).cast("long")).select("uid", "key", "w"), "keyed")
        return tables.snapshot(b.drop("part").join(slicing.slice_curve(keyed, parts).select("uid", "part"), "uid").select(*b.columns), "blocks")

    blocks = mesh.select("uid", F.lit(0).alias("level"), *[f"g{i}" for i in range(dims)], "v", F.lit(0).alias("part"))
    ctl, out = amortise.Controller(balance_cost, mode="compute", policy=policy), []
    for s in range(steps):
        t = [time.perf_counter()]
        blocks = tables.snapshot(adapt(blocks, dims, side, ball_centre(s, steps), radius), "blocks")
        if not s:
            blocks = cut(blocks)
        t.append(time.perf_counter())
        apart = blocks.withColumn("g0", F.col("g0") + F.col("level") * far)
        blocks = stencil(apart, dims, ("level", "part")).withColumn("g0", F.col("g0") - F.col("level") * far).select(*blocks.columns)
        blocks = tables.snapshot(blocks, "blocks")
        t.append(time.perf_counter())
        load = blocks.groupBy("part").agg(F.count("*").alias("n"), F.sum("level").alias("fine")).agg(F.max("n").alias("hi"), F.sum("n").alias("n"), F.sum("fine").alias("fine")).first()
        now = ctl.observe(load["hi"] * parts / load["n"] if clock == "model" else t[2] - t[1])
        t.append(time.perf_counter())
        if now:
            blocks = cut(blocks)
            ctl.rebalanced(ctl.balance_cost if clock == "model" else time.perf_counter() - t[3])
        t.append(time.perf_counter())
        out.append({"step": s, "blocks": load["n"], "fine": load["fine"], "cost": ctl.trace[-1]["cost"], "rebalanced": now, "refine_s": t[1] - t[0], "stencil_s": t[2] - t[1], "balance_s": t[4] - t[3]})
    return blocks, out


def step_loads(keyed: DataFrame, dims: int, parts: int, steps: int, radius: float, levels: int = 1) -> DataFrame:
    """step, part, w: loads of slices cut once, for the weights of step 0, as the ball moves on. One pass for all steps."""
    first = moving_ball(keyed, dims, ball_centre(0, steps), radius, levels)
    cut = tables.snapshot(slicing.slice_curve(first, parts).select("uid", *[f"c{i}" for i in range(dims)], "part"), "cut")
    out = None
    for s in range(steps):
        g = moving_ball(cut, dims, ball_centre(s, steps), radius, levels).groupBy("part").agg(F.sum("w").alias("w")).select(F.lit(s).alias("step"), "part", "w")
        out = g if out is None else out.unionByName(g)
    return out


#: Blocks of the order that one pass counts, and rows of a block that is small enough to be read.
BLOCKS, BLOCK_ROWS = 1 << 16, 1 << 10


def ordered(keyed: DataFrame, dims: int) -> DataFrame:
    """c0.., rank of keyed points, written once: the order does not change with the weights, so a cut is P - 1 ranks of it."""
    k = with_prefix(keyed.withColumn("_one", F.lit(1)), "key", "_one", "uid", "rank")
    return tables.snapshot(k.select(*[f"c{i}" for i in range(dims)], F.col("rank").cast("long").alias("rank")), "ordered")


def _first_ranks(weighted: DataFrame, goals: list[int], sums: dict[int, int], size: int, n: int) -> list[int]:
    """For each goal the first rank with at least that weight before it (n, if there is none). `sums`: weights of blocks of `size` ranks; only blocks in which
    a goal lies are read, in parts of themselves as long as they are large."""
    at, spans = {}, [(0, 0, sums)]  # goal -> rank; first block, weight before it, weights of blocks
    while True:
        hit: dict[int, int] = {}  # block -> weight before it
        found: dict[int, list[int]] = {}
        for _, before, part in spans:
            for b in sorted(part):
                for g in goals:
                    if g not in at and before < g <= before + part[b]:
                        hit[b] = before
                        found.setdefault(b, []).append(g)
                before += part[b]
        if size == 1:
            for b, gs in found.items():
                at |= {g: b + 1 for g in gs}
            return [0 if g <= 0 else at.get(g, n) for g in goals]
        step = max(1, size // BLOCK_ROWS)
        near = F.lit(False)
        for b in hit:
            near = near | F.col("rank").between(b * size, (b + 1) * size - 1)
        rows = weighted.where(near).groupBy(F.expr(f"rank div {size}L").alias("b"), F.expr(f"rank div {step}L").alias("s")).agg(F.sum("w").alias("w")).collect() if hit else []
        spans = [(b, before, {r["s"]: r["w"] for r in rows if r["b"] == b}) for b, before in hit.items()]
        size = step


def _weights(dims: int, steps: range, of: int, radius: float, levels: int, points: DataFrame) -> DataFrame:
    """Points with a column w<step> for each step."""
    for s in steps:
        points = moving_ball(points, dims, ball_centre(s, of), radius, levels).withColumnRenamed("w", f"w{s}")
    return points


def block_sums(points: DataFrame, dims: int, steps: range, of: int, radius: float, levels: int = 1) -> tuple[int, dict[int, np.ndarray]]:
    """Ranks of a block, and the weight of each block at each of the steps: one pass. The weights do not depend on the cuts."""
    n = points.agg(F.max("rank")).first()[0]
    size, n = BLOCK_ROWS, 0 if n is None else n + 1
    while n > size * BLOCKS:
        size *= BLOCK_ROWS
    w = _weights(dims, steps, of, radius, levels, points)
    rows = w.groupBy(F.expr(f"rank div {size}L").alias("b")).agg(*[F.sum(f"w{s}").alias(f"w{s}") for s in steps]).collect()
    b = np.array([r["b"] for r in rows], np.int64)
    out = {s: np.zeros(-(-n // size), np.int64) for s in steps}
    for s in steps:
        out[s][b] = [r[f"w{s}"] for r in rows]
    return size, out


def run(keyed: DataFrame, dims: int, parts: int, steps: int, radius: float, policy: str = "amortised", levels: int = 1, balance_cost: float | None = None, clock: str = "model", sums: tuple[int, dict[int, np.ndarray]] | None = None) -> list[dict]:
    """The loop on weighted points, which stand for the blocks of their place: new weights, loads, and a rebalance if the policy says so. `mesh_run` has real
    blocks and the stencil. The points stand in curve order once (`ordered`) and weights are expressions, added up by blocks of the order (`sums`, if they are there
    already; else one pass for all steps, or one a step on the wall clock). A rebalance re-cuts the order: it reads the blocks in which cuts lie. The
    model clock charges a step its heaviest load over the mean, and a rebalance `balance_cost`; the wall clock measures both."""
    points = keyed if "rank" in keyed.columns else ordered(keyed, dims)
    ahead = steps if clock == "model" else 1
    size, blocks = sums or (0, {})
    cuts: list[int] | None = None
    ctl = amortise.Controller(balance_cost if balance_cost is not None else 1.0, mode="compute", policy=policy)
    out = []

    def cut(s: int) -> list[int]:
        total, n = int(blocks[s].sum()), len(blocks[s]) * size
        w = moving_ball(points, dims, ball_centre(s, steps), radius, levels)
        return _first_ranks(w, [-(-total * i // parts) for i in range(1, parts)], dict(enumerate(blocks[s].tolist())), size, n)

    def shared(cuts: list[int], some: range) -> tuple[np.ndarray, list]:
        """The part of each block, -1 where a cut lies inside, and the sums of those by part."""
        start = np.arange(len(blocks[some[0]])) * size
        low, high = np.searchsorted(cuts, start, "right"), np.searchsorted(cuts, start + size - 1, "right")
        mixed = np.flatnonzero(low != high)
        near = F.lit(False)
        for b in mixed.tolist():
            near = near | F.col("rank").between(b * size, (b + 1) * size - 1)
        part = range_of(F.col("rank"), [c - 1 for c in cuts]).alias("part")
        rows = _weights(dims, some, steps, radius, levels, points.where(near)).groupBy(part).agg(*[F.sum(f"w{s}").alias(f"w{s}") for s in some]).collect() if len(mixed) else []
        return np.where(low == high, low, -1), rows

    for s in range(steps):
        t = [time.perf_counter()]
        some = range(s, min(s + ahead, steps))
        if s not in blocks:
            size, blocks = block_sums(points, dims, some, steps, radius, levels)
        if cuts is None:
            cuts, split = cut(s), None
        if split is None or ahead == 1:
            split = shared(cuts, some)
        whole = split[0] >= 0
        loads = np.bincount(split[0][whole], blocks[s][whole], parts).astype(np.int64)
        for r in split[1]:
            loads[r["part"]] += r[f"w{s}"]
        loads = loads.tolist()
        t.append(time.perf_counter())
        now = ctl.observe(max(loads) / (sum(loads) / parts) if clock == "model" else t[1] - t[0])
        if now:
            cuts, split = cut(s), None
            t.append(time.perf_counter())
            ctl.rebalanced(ctl.balance_cost if clock == "model" else t[2] - t[1])
        out.append({"step": s, "cost": ctl.trace[-1]["cost"], "debt": ctl.trace[-1]["debt"], "rebalanced": now, "loads": loads, "compute_s": t[1] - t[0], "balance_s": t[2] - t[1] if now else 0.0})
    return out
