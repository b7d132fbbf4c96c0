"""Sparse matrix times vector on a partition of the non-zeros: intervals, owners, communication and the product itself."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from curvebalance.plans import tables


def owner_of(idx: Column, n: int, parts: int) -> Column:
    """The owner of a vector entry: chunks of equal length, found by arithmetic."""
    return F.expr(f"CAST(({idx._jc.toString()} * {parts}L) div {max(1, n)}L AS INT)")


def demand(coo: DataFrame, side: str = "x") -> DataFrame:
    """part, idx: the vector entries each part needs; columns for x, rows for y."""
    return coo.select("part", F.col("col" if side == "x" else "row").alias("idx")).distinct()


def required_intervals(coo: DataFrame, side: str = "x", max_gap: int = 0) -> DataFrame:
    """part, lo, hi: runs of needed entries; gaps of up to max_gap entries are bridged."""
    w = W.partitionBy("part").orderBy("idx")
    d = demand(coo, side).withColumn("new", (F.col("idx") - F.lag("idx").over(w) > max_gap + 1).cast("int"))
    d = d.withColumn("run", F.sum(F.coalesce("new", F.lit(0))).over(w))
    return d.groupBy("part", "run").agg(F.min("idx").alias("lo"), F.max("idx").alias("hi")).select("part", "lo", "hi")


def with_owner(need: DataFrame, n: int, parts: int, owners: DataFrame | None = None) -> DataFrame:
    """Adds chunk and owner; owners: chunk, owner, if chunks were given to other parts."""
    d = need.withColumn("chunk", owner_of(F.col("idx"), n, parts))
    if owners is None:
        return d.withColumn("owner", F.col("chunk"))
    return d.join(F.broadcast(owners.select("chunk", "owner")), "chunk")  # a row a part


def dependents(coo: DataFrame, n: int, parts: int, side: str = "x", owners: DataFrame | None = None) -> DataFrame:
    """part, idx, owner of entries that a part needs and another owns."""
    return with_owner(demand(coo, side), n, parts, owners).where("owner != part").select("part", "idx", "owner")


def messages(coo: DataFrame, n: int, parts: int, side: str = "x", owners: DataFrame | None = None) -> DataFrame:
    """src (owner), dst (part), n entries."""
    return dependents(coo, n, parts, side, owners).groupBy(F.col("owner").alias("src"), F.col("part").alias("dst")).agg(F.count("*").alias("n"))


def overlap(coo: DataFrame, n: int, parts: int, side: str = "x") -> DataFrame:
    """chunk, part, overlap: how much of each chunk each part needs; P * P rows at most."""
    d = with_owner(demand(coo, side), n, parts)
    return d.groupBy("chunk", "part").agg(F.count("*").alias("overlap"))


def reassign_owners(coo: DataFrame, n: int, parts: int, rule: str = "overlap", side: str = "x") -> DataFrame:
    """chunk, owner: each chunk to the part that needs most of it, the smallest of equals; one_to_one: each part gets one chunk at most, largest
    overlaps first. A chunk that nobody needs stays."""
    o = overlap(coo, n, parts, side)
    spark = coo.sparkSession
    if rule == "overlap":
        w = W.partitionBy("chunk").orderBy(F.desc("overlap"), "part")
        best = o.withColumn("rn", F.row_number().over(w)).where("rn = 1").select("chunk", F.col("part").alias("owner"))
        every = spark.range(parts).select(F.col("id").cast("int").alias("chunk"))
        return every.join(best, "chunk", "left").select("chunk", F.coalesce("owner", "chunk").alias("owner"))
    if rule != "one_to_one":
        raise ValueError("unknown rule")
    rows = sorted(((r["overlap"], r["chunk"], r["part"]) for r in o.collect()), key=lambda t: (-t[0], t[1], t[2]))
    got, used = {}, set()
    for _, c, p in rows:
        if c not in got and p not in used:
            got[c] = p
            used.add(p)
    free = [p for p in range(parts) if p not in used]
    for c in range(parts):
        if c not in got:
            got[c] = c if c in free else free[0]
            free.remove(got[c])
    return spark.createDataFrame([(c, p) for c, p in sorted(got.items())], "chunk int, owner int")


def spanning_set(coo: DataFrame, n: int, parts: int, w_mem: float = 1.0, w_net: float = 10.0, iters: int = 8, side: str = "x") -> tuple[dict[int, int], float]:
    """Owners that lower the total of weighted edges between interval requests and parts: memory weight where the owner needs the entries
    itself, network weight for all others. From equal chunks, single moves and swaps that help are made until none does or the rounds end."""
    need = {(r["chunk"], r["part"]): r["overlap"] for r in overlap(coo, n, parts, side).collect()}
    chunk = {c: sum(v for (k, _), v in need.items() if k == c) for c in range(parts)}
    cost = lambda c, p: w_net * (chunk[c] - need.get((c, p), 0)) + w_mem * need.get((c, p), 0)
    own = {c: c for c in range(parts)}
    for _ in range(iters):
        better = False
        for a in range(parts):
            for b in range(a + 1, parts):
                if cost(a, own[b]) + cost(b, own[a]) < cost(a, own[a]) + cost(b, own[b]):
                    own[a], own[b] = own[b], own[a]
                    better = True
        if not better:
            break
    return own, sum(cost(c, p) for c, p in own.items())


def multiply(coo: DataFrame, x: DataFrame) -> DataFrame:
    """row, y: local products by (part, row), then a sum a row at its owner. x (idx, x) meets the non-zeros by a join; entries
    nobody needs are never moved."""
    j = coo.join(x.withColumnRenamed("idx", "col"), "col")
    local = j.groupBy("part", "row").agg(F.sum(F.col("val") * F.col("x")).alias("s"))
    return local.groupBy("row").agg(F.sum("s").alias("y"))


def scatter(y: DataFrame, coo: DataFrame, n: int, parts: int, owners: DataFrame | None = None) -> DataFrame:
    """part, idx, y: results brought back to the parts that hold replicas of them."""
    return dependents(coo, n, parts, "y", owners).join(y.withColumnRenamed("row", "idx"), "idx").select("part", "idx", "y")


def power_iterate(coo: DataFrame, x: DataFrame, k: int) -> DataFrame:
    """x after k products, each scaled to a largest entry of 1; lineage ends in a snapshot every time. Rows without non-zeros become 0."""
    for _ in range(k):
        y = tables.snapshot(multiply(coo, x), "power")
        top = y.agg(F.max(F.abs("y"))).first()[0] or 1.0
        x = y.select(F.col("row").alias("idx"), (F.col("y") / F.lit(float(top))).alias("x"))
    return x


def comm_trees(coo: DataFrame, n: int, parts: int, owners: DataFrame | None = None) -> DataFrame:
    """owner, leaves (parts with replicas), entries: one reduction or broadcast tree an owner."""
    d = dependents(coo, n, parts, "x", owners)
    return d.groupBy("owner").agg(F.sort_array(F.collect_set("part")).alias("leaves"), F.count("*").alias("entries"))


def concurrent_trees(trees: list[tuple[int, list[int]]]) -> list[list[int]]:
    """Rounds of trees (owner, leaves) that share no part and can run at once; first fit, in the order of owners. A row a part."""
    rounds: list[tuple[set[int], list[int]]] = []
    for o, leaves in sorted(trees):
        s = {o, *leaves}
        for used, own in rounds:
            if not used & s:
                used |= s
                own.append(o)
                break
        else:
            rounds.append((set(s), [o]))
    return [own for _, own in rounds]


def intervals_table(coo: DataFrame, n: int, parts: int, side: str = "x") -> DataFrame:
    """part, side, lo, hi, owned: each part's own chunk and its required runs."""
    own = coo.sparkSession.range(parts).select(F.col("id").cast("int").alias("part"), F.lit(side).alias("side"), F.expr(f"(id * {n}L + {parts - 1}L) div {parts}L").alias("lo"), F.expr(f"((id + 1) * {n}L + {parts - 1}L) div {parts}L - 1").alias("hi"), F.lit(True).alias("owned"))
    return own.unionByName(required_intervals(coo, side).select("part", F.lit(side).alias("side"), "lo", "hi", F.lit(False).alias("owned")))
