"""Best-fit packing of token sequences with large-item matching.

A document's ids, with the end id, are cut into pieces of the capacity only if they exceed it (the first piece is the shorter one). Items
above one third of the capacity fit in a bin at most twice: they are matched greedily, the largest with the largest that still fits. The others
go, largest first, where the least space remains. All items of a length are alike, so the bins are found from the number of items of
each length: a histogram of `capacity` numbers on the driver, whatever the corpus' size. Groups of equal bins have consecutive
sequence ids; an item's place follows from its rank among the items of its length. Ranks come from counts by (length, hash bucket), so
no task holds all items of a common length.

Null or empty texts are one piece, the end id alone. Null ids and repeated rows are packed like others. Empty tables give no rows.
"""

from __future__ import annotations

import bisect
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from . import common as C, tokens as T

#: Pieces a hash bucket should hold; buckets, at least 64, grow with the table.
BUCKET_ROWS = 250_000


def pieces(docs: DataFrame, encoder: T.ByteBpe, capacity: int, end_id: int, keep_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids, unsigned 32-bit little-endian) of every piece."""

    def run(batches):
        for x in C.freed(batches):
            ids = x.column(0)
            for at, texts in T.slices_of(x.column(1)):
                who, rows = [], []
                for i, a in enumerate(encoder.encode(texts)):
                    a = np.append(a, np.uint32(end_id)).astype("<u4")
                    first = len(a) % capacity or min(capacity, len(a))
                    cuts = [0, *range(first, len(a) + 1, capacity)]
                    for k, (s, e) in enumerate(zip(cuts, cuts[1:])):
                        who.append(at + i)
                        b = a[s:e].tobytes()
                        rows.append((k, s, e - s, zlib.crc32(b), b if keep_ids else None))
                cols = list(zip(*rows))
                out = {"doc_id": ids.take(pa.array(who)), "piece": pa.array(cols[0], pa.int32()), "start": pa.array(cols[1], pa.int64()), "length": pa.array(cols[2], pa.int64()), "ids_crc32": pa.array(cols[3], pa.int64())}
                if keep_ids:
                    out["ids"] = pa.array(cols[4], pa.binary())
                yield C.batch_of(out)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * keep_ids
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def plan_bins(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int]], int]:
    """Places for all items, from the number of items by length: runs (length, first rank, first sequence, offset), each up to
    the next run's first rank, and the number of sequences."""
    left = {n: c for n, c in counts.items() if c > 0}
    used = dict.fromkeys(left, 0)
    runs: list[tuple[int, int, int, int]] = []
    gaps: dict[int, list[tuple[int, int]]] = {}  # free space -> groups of bins (first sequence, number)
    order: list[int] = []
    bins = 0

    def place(n: int, number: int, seq: int, offset: int) -> None:
        runs.append((n, used[n], seq, offset))
        used[n] += number
        left[n] -= number

    def free(space: int, seq: int, number: int) -> None:
        if space and number:
            if space not in gaps:
                gaps[space] = []
                bisect.insort(order, space)
            gaps[space].append((seq, number))

    large = sorted(n for n in left if 3 * n > capacity)
    for n in reversed(large):
        while left[n]:
            i = bisect.bisect_right(large, capacity - n) - 1
            while i >= 0 and not left[large[i]]:
                i -= 1
            mate = large[i] if i >= 0 else 0
            if mate == n and left[n] == 1:  # it can't be its own mate
                i -= 1
                while i >= 0 and not left[large[i]]:
                    i -= 1
                mate = large[i] if i >= 0 else 0
            number = left[n] if not mate else left[n] // 2 if mate == n else min(left[n], left[mate])
            place(n, number, bins, 0)
            if mate:
                place(mate, number, bins, n)
            free(capacity - n - mate, bins, number)
            bins += number
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        while left[n]:
            i = bisect.bisect_left(order, n)
            if i == len(order):
                each = capacity // n
                number = max(1, left[n] // each)
                free(capacity, bins, number)
                bins += number
                continue
            space = order[i]
            seq, there = gaps[space].pop()
            if not gaps[space]:
                del gaps[space]
                order.pop(i)
            number = min(there, left[n])
            place(n, number, seq, capacity - space)
            free(space, seq + number, there - number)
            free(space - n, seq, number)
    return runs, bins


def pack(items: DataFrame, capacity: int) -> DataFrame:
    """Adds sequence_id and offset to a stashed table of pieces with `length` (1 to capacity), doc_id, piece and ids_crc32."""
    n = max(64, items.count() // BUCKET_ROWS)
    items = items.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(n)))
    counts = C.stash(items.groupBy("length", "bucket").agg(F.count("*").alias("c")), "lengths")
    runs, _ = plan_bins({r["length"]: r["c"] for r in counts.groupBy("length").agg(F.sum("c").alias("c")).collect()}, capacity)
    runs.sort()
    key = np.array([a << 40 | b for a, b, _, _ in runs], np.int64)
    seq, off, low = (np.array([r[i] for r in runs], np.int64) for i in (2, 3, 1))
    before = counts.withColumn("before", F.coalesce(F.sum("c").over(W.partitionBy("length").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).drop("c")
    rank = F.row_number().over(W.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = items.withColumn("rank", rank).join(before, ["length", "bucket"]).withColumn("rank", F.col("rank") + F.col("before"))
    keep = [c for c in items.columns if c != "bucket"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in items.schema if f.name != "bucket") + ", sequence_id long, offset long"

    def run(batches):
        for x in C.freed(batches):
            length, r = x.column("length").to_numpy(), x.column("rank").to_numpy()
            i = np.searchsorted(key, length << 40 | r, "right") - 1
            yield C.batch_of({c: x.column(c) for c in keep} | {"sequence_id": pa.array(seq[i] + r - low[i]), "offset": pa.array(off[i])})

    return ranked.select(*keep, "rank").mapInArrow(run, schema)


def pack_documents(docs: DataFrame, vocabulary: str, ranks: str | None = None, capacity: int = 2048, end_id: int = 0, keep_ids: bool = False) -> DataFrame:
    """Pieces of all documents with their places: doc_id, piece, start, length, ids_crc32[, ids], sequence_id, offset."""
    C.ship(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return pack(C.stash(pieces(docs, T.ByteBpe(vocabulary, ranks), capacity, end_id, keep_ids), "pieces"), capacity)


def sequences(packed: DataFrame) -> DataFrame:
    """sequence_id and its whole ids (unsigned 32-bit little-endian) from packed pieces that keep their ids."""
    parts = F.sort_array(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(parts.alias("p")).select("sequence_id", F.aggregate("p", F.lit(b""), lambda a, p: F.concat(a, p["ids"])).alias("ids"))
