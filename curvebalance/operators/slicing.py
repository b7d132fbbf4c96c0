"""Order points along a curve and cut the weighted order into contiguous slices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from curvebalance.plans.prefix import with_prefix

RULES = ("prefix", "midweight", "close", "refined")


def total_weight(df: DataFrame) -> int:
    return df.agg(F.sum("w")).first()[0] or 0


def order_points(keyed: DataFrame, n: int | None = None) -> DataFrame:
    """uid, key, rank (from 0) in curve order, ties by uid."""
    return with_prefix(keyed.withColumn("_one", F.lit(1)), "key", "_one", "uid", "rank", n).select("uid", "key", F.col("rank").cast("long").alias("rank"))


def part_of(prefix: Column, total: int, parts: int) -> Column:
    """floor(P * prefix / W) in integers; decimals, where the product may exceed 63 bits."""
    if total * parts < 1 << 62:
        return F.least(F.lit(parts - 1), F.expr(f"({_sql(prefix)} * {parts}L) div {max(1, total)}L").cast("int"))
    wide = F.floor(prefix.cast("decimal(28,0)") * F.lit(parts).cast("decimal(9,0)") / F.lit(total).cast("decimal(28,0)"))
    return F.least(F.lit(parts - 1), wide.cast("int"))


def _sql(c: Column) -> str:
    return c._jc.toString()


def slice_curve(keyed: DataFrame, parts: int, rule: str = "prefix", n: int | None = None) -> DataFrame:
    """Adds prefix and part to keyed points (uid, key, w). prefix: by the weight before a point; midweight: by its middle; close: a slice ends
    once it has its share of what is left; refined: the cuts of `prefix`, moved until loads differ by the heaviest point at most."""
    if rule not in RULES or parts < 1:
        raise ValueError("unknown rule or number of parts")
    df = with_prefix(keyed, "key", "w", "uid", "prefix", n)
    total = total_weight(keyed)
    if rule == "midweight":
        return df.withColumn("_m", F.col("prefix") * 2 + F.col("w")).withColumn("part", part_of(F.col("_m"), 2 * total, parts)).drop("_m")
    if rule == "prefix":
        return df.withColumn("part", part_of(F.col("prefix"), total, parts))
    cuts = _close_cuts(df, total, parts) if rule == "close" else _refined_cuts(df, total, parts)
    part = F.lit(0)
    for i, c in enumerate(cuts):
        part = F.when(F.col("prefix") >= F.lit(int(c)), F.lit(i + 1)).otherwise(part)
    return df.withColumn("part", part)


def _edges(df: DataFrame, near: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """(prefix, w) of points whose prefix lies in one of the given ranges; few, around the cuts."""
    cond = F.lit(False)
    for a, b in near:
        cond = cond | ((F.col("prefix") >= int(a)) & (F.col("prefix") <= int(b)))
    return sorted((int(r["prefix"]), int(r["w"])) for r in df.where(cond).select("prefix", "w").collect())


def _close_cuts(df: DataFrame, total: int, parts: int) -> list[int]:
    """Greedy fill: the next cut is the first point at which the slice has its share of the rest, or the one before if that is closer."""
    heavy = df.agg(F.max("w")).first()[0] or 0
    cuts, start = [], 0
    for i in range(parts - 1):
        goal = start + (total - start) / (parts - i)
        rows = _edges(df, [(goal - heavy, goal + heavy)])
        ends = [p + w for p, w in rows if p + w >= goal]
        before = [p for p, w in rows if p <= goal and p >= start]
        up, down = min(ends, default=total), max(before, default=start)
        start = up if up - goal <= goal - down or down <= start else down
        cuts.append(start)
    return cuts


def _refined_cuts(df: DataFrame, total: int, parts: int) -> list[int]:
    """Moves cuts by one point between the heaviest and the lightest slice until loads differ by the heaviest weight at most."""
    heavy = df.agg(F.max("w")).first()[0] or 0
    goals = [-(-total * i // parts) for i in range(1, parts)]
    reach = 4 * heavy + 1
    rows = _edges(df, [(g - reach, g + reach) for g in goals])
    starts = sorted({p for p, _ in rows} | {p + w for p, w in rows} | {0, total})
    at = [min(range(len(starts)), key=lambda i: (abs(starts[i] - g), i)) for g in goals]
    for _ in range(8 * parts):
        edge = [0, *[starts[i] for i in at], total]
        load = [b - a for a, b in zip(edge, edge[1:])]
        if max(load) - min(load) <= heavy:
            break
        i, j = load.index(max(load)), load.index(min(load))
        step = 1 if i > j else -1  # every cut between them moves towards the heavy slice
        for k in range(min(i, j), max(i, j)):
            at[k] = min(len(starts) - 1, max(0, at[k] + step))
    return [starts[i] for i in at]


def slice_cells(cells: list[tuple[int, int]], parts: int) -> dict[int, int]:
    """Greedy slices of (cell, weight) in key order on the driver: cell -> part."""
    total, before, out = sum(w for _, w in cells), 0, {}
    for c, w in cells:
        out[c] = min(parts - 1, before * parts // max(1, total))
        before += w
    return out


def slice_buckets(members: DataFrame, parts: int, n: int | None = None) -> DataFrame:
    """Slices of whole buckets: key, n, w, prefix, part of each bucket (rows with one key)."""
    b = members.groupBy("key").agg(F.count("*").alias("n"), F.sum("w").alias("w"), F.min("uid").alias("uid"))
    return slice_curve(b, parts, "prefix", n)


def loads(assigned: DataFrame, parts: int) -> DataFrame:
    """part, n, w of every slice; empty ones are there with 0."""
    have = assigned.groupBy("part").agg(F.count("*").alias("n"), F.sum("w").alias("w"))
    every = assigned.sparkSession.range(parts).select(F.col("id").cast("int").alias("part"))
    return every.join(have, "part", "left").select("part", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("w", F.lit(0)).cast("long").alias("w"))


def slice_table(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("part").agg(F.count("*").alias("n"), F.sum("w").alias("w"), F.min("key").alias("key_lo"), F.max("key").alias("key_hi"))

