"""Mixing sources to target weights by temperature.

A source's share of the tokens is raised to an exponent and normalised to its weight. An exponent of 1 keeps the shares, 0 makes all sources
equal. The exponent is found by repeated sectioning (a bisection with many points a round, one aggregate over the sources each): the
largest that meets a target entropy, or larger where a source would otherwise be repeated more often than a limit.

The weights are realised in block permutations. A source's documents are dealt by hash to blocks; an epoch takes all blocks, by their
`turn`, a hash of epoch and block, so that each has an order of its own, and in a block documents by `order`; a last, partial epoch takes blocks by their
turn while the token budget lasts and, of the block where it ends, documents in hashed order while they fit. So no source, however hot, is sorted or
summed as a whole: only its blocks are, in `RANGES` ranges of their turns, and the one block that is cut.
The budget is the smallest for which every source is used at least once (`keep_all`), or a number of tokens.

Tokens are white-space-separated words. A null source is a source of its own. Documents without tokens are in all full epochs.
Repeated rows are documents of their own. An empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from . import common as C

BLOCK_DOCS, SECTIONS, STEPS, RANGES = 2000, 32, 6, 1024


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def shares(docs: DataFrame) -> DataFrame:
    """source, docs, tokens; null sources together."""
    return docs.groupBy("source").agg(F.count("*").alias("docs"), F.sum("tokens").alias("tokens"))


def _measures(sources: DataFrame, exponents: list[float]) -> list[tuple[float, float, float]]:
    """(exponent, entropy in nats, largest number of epochs, if the least used source has one) of each exponent, in one aggregate."""
    total = F.broadcast(sources.agg(F.sum("tokens").alias("all")))  # one row
    p = sources.where("tokens > 0").crossJoin(total).withColumn("p", F.col("tokens") / F.col("all"))
    p = p.withColumn("e", F.explode(F.array(*[F.lit(float(x)) for x in exponents]))).withColumn("w", F.pow("p", "e"))
    # entropy of w / sum(w), and w / p at its extremes
    rows = p.groupBy("e").agg(F.sum("w").alias("s"), F.sum(F.col("w") * F.log("w")).alias("l"), F.max(F.col("w") / F.col("p")).alias("hi"), F.min(F.col("w") / F.col("p")).alias("lo")).collect()
    return sorted((r["e"], math.log(r["s"]) - r["l"] / r["s"], r["hi"] / r["lo"]) for r in rows)


def exponent(sources: DataFrame, entropy: float | None = None, most_epochs: float | None = None) -> float:
    """The exponent in [0, 1] for a target entropy (share of the largest possible, log of the number of sources) and a limit on epochs."""
    n = sources.where("tokens > 0").count()
    if n < 2:
        return 1.0
    goal = None if entropy is None else entropy * math.log(n)

    def section(good) -> float:
        """Where a property that holds at one end of [0, 1] alone changes."""
        lo, hi = 0.0, 1.0
        for _ in range(STEPS):
            grid = [lo + (hi - lo) * i / SECTIONS for i in range(SECTIONS + 1)]
            ok = [good(*m) for m in _measures(sources, grid)]
            cut = next((i for i in range(SECTIONS + 1) if not ok[i]), SECTIONS + 1)
            if cut == 0:
                return lo
            if cut > SECTIONS:
                return hi
            lo, hi = grid[cut - 1], grid[cut]
        return lo

    # entropy falls with the exponent: the largest that still has the wanted one; epochs fall too: the smallest within the limit
    a = 1.0 if goal is None else section(lambda e, h, r: h >= goal - 1e-12)
    if most_epochs is None:
        return a
    _, _, at = _measures(sources, [a])[0]
    if at <= most_epochs:
        return a
    lo, hi = 0.0, 1.0
    for _ in range(STEPS):
        grid = [lo + (hi - lo) * i / SECTIONS for i in range(SECTIONS + 1)]
        ok = [r <= most_epochs * (1 + 1e-12) for _, _, r in _measures(sources, grid)]
        cut = next((i for i in range(SECTIONS + 1) if ok[i]), SECTIONS)
        if cut == 0:
            return max(a, lo)
        lo, hi = grid[cut - 1], grid[cut]
    return max(a, hi)


def weights(sources: DataFrame, power: float, budget: int | None = None) -> DataFrame:
    """source, docs, tokens, weight, quota (tokens to draw), epochs (full ones) and rest (tokens of the partial one)."""
    total = F.broadcast(sources.agg(F.sum("tokens").alias("all"), F.sum(F.when(F.col("tokens") > 0, F.pow(F.col("tokens").cast("double"), F.lit(power)))).alias("z"), F.max(F.when(F.col("tokens") > 0, F.col("tokens") / F.pow(F.col("tokens").cast("double"), F.lit(power)))).alias("r")))
    w = sources.crossJoin(total).withColumn("weight", F.when(F.col("tokens") > 0, F.pow(F.col("tokens").cast("double"), F.lit(power)) / F.col("z")).otherwise(0.0))
    # tokens / weight is largest for the source that is used least often
    b = F.col("r") * F.col("z") if budget is None else F.lit(float(budget))
    w = w.withColumn("quota", F.when(F.col("tokens") > 0, F.round(F.col("weight") * b)).otherwise(0).cast("long"))
    w = w.withColumn("epochs", F.when(F.col("tokens") > 0, F.floor(F.col("quota") / F.col("tokens"))).otherwise(1).cast("int"))
    return w.withColumn("rest", F.col("quota") - F.col("epochs") * F.col("tokens")).select("source", "docs", "tokens", "weight", "quota", "epochs", "rest")


def mix(docs: DataFrame, entropy: float | None = 0.95, most_epochs: float | None = 2.0, budget: int | None = None, seed: int = 0) -> DataFrame:
    """Rows of `docs` (doc_id, source, text and others) as often as the mixture has them, with tokens, epoch, block, turn and order: an epoch
    of a source takes its blocks by (turn, block), a block's documents by order. Columns of `docs` with these five names are left out."""
    spark = docs.sparkSession
    docs, names = C.apart(docs.select(*[c for c in docs.columns if c.lower() not in ("tokens", "epoch", "block", "turn", "order")]), ("doc_id", "source", "text"))
    size = docs.withColumn("tokens", words(F.col("text")))
    src = C.stash(shares(size), "sources")
    plan = C.stash(weights(src, exponent(src, entropy, most_epochs), budget), "mixture")
    # keys by which sources meet: null is a source too
    same = [F.coalesce(F.col("source"), F.lit("")).alias("s0"), F.col("source").isNull().alias("s1")]
    w = plan.select(*same, F.greatest(F.lit(1), F.ceil(F.col("docs") / BLOCK_DOCS)).alias("blocks"), "epochs", "rest")
    w = C.maybe_broadcast(C.stash(w, "mixture"), 200)
    key = F.xxhash64(F.lit(seed), "doc_id", "text")
    rows = size.select("*", *same).join(w, ["s0", "s1"]).withColumn("hash", key).withColumn("block", F.pmod("hash", F.col("blocks")).cast("long"))
    narrow = rows.where("rest > 0").select("s0", "s1", "block", "hash", "tokens", "rest", "epochs", "doc_id")
    turn = lambda epoch: F.xxhash64(F.lit(seed), F.col(epoch), "block")
    sums = narrow.groupBy("s0", "s1", "block").agg(F.sum("tokens").alias("n"), F.first("rest").alias("rest"), F.first("epochs").alias("epochs")).withColumn("turn", turn("epochs"))
    sums = C.stash(sums.withColumn("range", F.floor((F.col("turn").cast("double") / 2.0**64 + 0.5) * RANGES).cast("int")), "block-sums")
    earlier = lambda of, *by: F.coalesce(F.sum("n").over(W.partitionBy(*of).orderBy(*by).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    # a source has as many rows here as there are ranges, at most
    ranges = sums.groupBy("s0", "s1", "range").agg(F.sum("n").alias("n")).withColumn("first", earlier(("s0", "s1"), "range")).select("s0", "s1", "range", "first")
    sums = sums.join(C.maybe_broadcast(C.stash(ranges, "ranges"), 60), ["s0", "s1", "range"])
    before = F.col("first") + earlier(("s0", "s1", "range"), "turn", "block")
    sums = sums.withColumn("left", F.col("rest") - before).where(F.col("left") > 0)
    sums = C.maybe_broadcast(C.stash(sums.select("s0", "s1", "block", "n", "left"), "blocks"), 200)
    full = sums.select("s0", "s1", "block", (F.col("n") <= F.col("left")).alias("whole"), "left")
    # of the block where the budget ends, documents in hashed order while they fit
    run = F.sum("tokens").over(W.partitionBy("s0", "s1", "block").orderBy("hash", "doc_id").rangeBetween(W.unboundedPreceding, 0))
    cut = narrow.join(full.where("not whole"), ["s0", "s1", "block"]).withColumn("run", run).groupBy("s0", "s1", "block").agg(F.max(F.when(F.col("run") <= F.col("left"), F.struct("hash", "doc_id"))).alias("last"))
    cut = C.stash(cut, "cut")
    ends = C.maybe_broadcast(C.stash(full.join(cut, ["s0", "s1", "block"], "left").select("s0", "s1", "block", "whole", "last"), "ends"), 200)
    rows = rows.join(ends, ["s0", "s1", "block"], "left")
    extra = (F.coalesce("whole", F.lit(False)) | F.coalesce(F.struct("hash", "doc_id") <= F.col("last"), F.lit(False))).cast("int")
    times = F.col("epochs") + extra
    out = rows.withColumn("n", times).where("n > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    own = [F.col(v).alias(k) for v, k in names.items()]
    return out.select(*own, "tokens", "epoch", "block", turn("epoch").alias("turn"), F.xxhash64(F.lit(seed), "epoch", "hash").alias("order"))
