"""Loads, communication, quality and accuracy measures. All are aggregates; what reaches the driver is a row a part or less."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window as W, functions as F

from .slicing import loads


def load(assigned: DataFrame, parts: int) -> DataFrame:
    """avg_load (floor), max_load, min_load, imbalance (largest pairwise difference)."""
    return loads(assigned, parts).agg((F.floor(F.sum("w") / parts)).cast("long").alias("avg_load"), F.max("w").alias("max_load"), F.min("w").alias("min_load"), (F.max("w") - F.min("w")).alias("imbalance"))


def check_partition(assigned: DataFrame, parts: int, limit: int | None = None) -> DataFrame:
    """Whether slices are disjoint (each id once), inside 0..P-1, and differ by at most `limit` (the heaviest point by default)."""
    ids = assigned.groupBy("uid").agg(F.count("*").alias("c")).agg(F.max("c").alias("most"))
    heavy = assigned.agg(F.max("w").alias("heavy"), F.min("part").alias("lo"), F.max("part").alias("hi"))
    one = ids.crossJoin(heavy).crossJoin(load(assigned, parts))  # three tables of one row
    bound = F.lit(limit) if limit is not None else F.col("heavy")
    return one.select((F.col("most") == 1).alias("disjoint"), ((F.col("lo") >= 0) & (F.col("hi") < parts)).alias("in_range"), (F.col("imbalance") <= bound).alias("balanced"))


def volume(edges: DataFrame, assigned: DataFrame) -> DataFrame:
    """part, volume: weight of the edges (src, dst, w) that leave each part, counted at both ends."""
    a = assigned.select(F.col("uid").alias("src"), F.col("part").alias("ps"))
    b = assigned.select(F.col("uid").alias("dst"), F.col("part").alias("pd"))
    cut = edges.join(a, "src").join(b, "dst").where("ps != pd")
    return cut.select(F.explode(F.array("ps", "pd")).alias("part"), "w").groupBy("part").agg(F.sum("w").alias("volume"))


def cut_edges(edges: DataFrame, assigned: DataFrame) -> DataFrame:
    """src_part, dst_part, n, w of the edges between parts."""
    a = assigned.select(F.col("uid").alias("src"), F.col("part").alias("src_part"))
    b = assigned.select(F.col("uid").alias("dst"), F.col("part").alias("dst_part"))
    return edges.join(a, "src").join(b, "dst").where("src_part != dst_part").groupBy("src_part", "dst_part").agg(F.count("*").alias("n"), F.sum("w").alias("w"))


def objective(cuts: DataFrame, alpha: float = 1.0, beta: float = 1.0) -> DataFrame:
    """max_cut, total_cut, max_in_degree, max_out_degree and alpha * total_cut + beta * max_out_degree of a part-to-part table (src_part, dst_part, w)."""
    out = cuts.groupBy("src_part").agg(F.sum("w").alias("w"), F.count_distinct("dst_part").alias("d"))
    inn = cuts.groupBy("dst_part").agg(F.count_distinct("src_part").alias("d"))
    a = out.agg(F.max("w").alias("max_cut"), F.sum("w").alias("total_cut"), F.max("d").alias("max_out_degree"))
    b = inn.agg(F.max("d").alias("max_in_degree"))
    return a.crossJoin(b).select("max_cut", "total_cut", "max_in_degree", "max_out_degree", (F.col("total_cut") * F.lit(alpha) + F.col("max_out_degree") * F.lit(beta)).alias("weighted"))


def surface_to_volume(cells: DataFrame, dims: int) -> DataFrame:
    """part, n, surface, ratio on a grid of cells (uid, g0.., part): faces towards other parts or outside, over cells. One equi join a direction."""
    out = None
    for i in range(dims):
        for s in (-1, 1):
            near = cells.select(*[(F.col(f"g{k}") + (s if k == i else 0)).alias(f"g{k}") for k in range(dims)], F.col("part").alias("own"))
            j = near.join(cells, [f"g{k}" for k in range(dims)], "left").where("part is null or part != own").select(F.col("own").alias("part"))
            out = j if out is None else out.unionByName(j)
    faces = out.groupBy("part").agg(F.count("*").alias("surface"))
    return cells.groupBy("part").agg(F.count("*").alias("n")).join(faces, "part", "left").select("part", "n", F.coalesce("surface", F.lit(0)).cast("long").alias("surface"), (F.coalesce("surface", F.lit(0)) / F.col("n")).alias("ratio"))


def tree_stats(members: DataFrame) -> DataFrame:
    """nodes, leaves, max_depth, max_bucket from the leaves alone: a full binary tree of L leaves has 2L - 1 nodes."""
    leaves = members.groupBy("path").agg(F.count("*").alias("n"), F.first("depth").alias("depth"))
    return leaves.agg((F.count("*") * 2 - 1).alias("nodes"), F.count("*").alias("leaves"), F.max("depth").cast("long").alias("max_depth"), F.max("n").alias("max_bucket"))


def split_balance(nodes: DataFrame) -> DataFrame:
    """depth, nodes and mean distance from one half of the lower child's share, over inner nodes (path, depth, n)."""
    low = nodes.where("path % 2 = 0").select(F.shiftright("path", 1).alias("path"), F.col("n").alias("low"))
    j = nodes.join(low, "path")
    return j.groupBy("depth").agg(F.count("*").alias("nodes"), F.round(F.avg(F.abs(F.col("low") / F.col("n") - 0.5)), 6).alias("error"))


def curve_steps(ordered: DataFrame, dims: int) -> DataFrame:
    """Share of steps to a face neighbour, and mean step (L1), over successive cells of ordered grid points (key, g0.., range).

    `range` cuts the order in contiguous pieces, so no window spans the table; the step between two pieces is not counted.
    """
    w = W.partitionBy("range").orderBy("key")
    step = sum((F.abs(F.col(f"g{i}") - F.lag(f"g{i}").over(w)) for i in range(1, dims)), F.abs(F.col("g0") - F.lag("g0").over(w)))
    return ordered.withColumn("step", step).where("step is not null").agg(F.count("*").alias("steps"), F.round(F.avg((F.col("step") == 1).cast("int")), 6).alias("unit_share"), F.round(F.avg("step"), 6).alias("mean_step"))


def knn_recall(approx: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """k, recall (share of true neighbours found) and ratio (mean of approximate over true k-th distance, roots taken)."""
    hit = exact.select("qid", "uid").join(approx.select("qid", "uid", F.lit(1).alias("hit")), ["qid", "uid"], "left").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))
    far = lambda d, n: d.groupBy("qid").agg(F.sqrt(F.max("d2")).alias(n))
    ratio = far(approx, "a").join(far(exact, "e"), "qid").where("e > 0").agg(F.avg(F.col("a") / F.col("e")).alias("ratio"))
    return hit.crossJoin(ratio).select(F.lit(k).alias("k"), F.round("recall", 6).alias("recall"), F.round("ratio", 6).alias("ratio"))


def full_replication_volume(n: int, parts: int) -> int:
    """Entries moved if every part gets the whole vector: all but its own chunk."""
    return n * (parts - 1)


def degree_and_messages(messages: DataFrame, parts: int) -> DataFrame:
    """max_degree (distinct peers, both directions), max_message (heaviest pair), max_volume (sent or received by one part) and
    total_volume of messages (src, dst, n)."""
    ends = messages.select(F.col("src").alias("part"), F.col("dst").alias("peer"), "n").unionByName(messages.select(F.col("dst").alias("part"), F.col("src").alias("peer"), "n"))
    by = ends.groupBy("part").agg(F.count_distinct("peer").alias("degree"))
    need = messages.groupBy("dst").agg(F.sum("n").alias("volume"))
    a = by.agg(F.coalesce(F.max("degree"), F.lit(0)).cast("long").alias("max_degree"))
    b = need.agg(F.coalesce(F.max("volume"), F.lit(0)).cast("long").alias("max_volume"), F.coalesce(F.sum("volume"), F.lit(0)).cast("long").alias("total_volume"))
    c = messages.agg(F.coalesce(F.max("n"), F.lit(0)).cast("long").alias("max_message"))
    return a.crossJoin(b).crossJoin(c)


def speedup(times: DataFrame) -> DataFrame:
    """size, time and speedup of a table (size, time): the time of the smallest configuration over each one's."""
    base = times.agg(F.min_by("time", "size").alias("base"))  # one row
    return times.crossJoin(F.broadcast(base)).select("size", "time", (F.col("base") / F.col("time")).alias("speedup"))
