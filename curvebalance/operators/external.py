"""Buckets packed to pages in curve order, and how many pages a batch of queries reads."""

from __future__ import annotations

from collections import OrderedDict

from pyspark.sql import DataFrame, functions as F

from curvebalance.plans.prefix import with_prefix


def paginate(buckets: DataFrame, page_bytes: int, row_bytes: int = 40) -> DataFrame:
    """Adds bytes and page to buckets (bucket, key_lo, n): the prefix of bytes in curve order over the page size."""
    b = buckets.withColumn("bytes", F.col("n") * F.lit(row_bytes).cast("long"))
    p = with_prefix(b, "key_lo", "bytes", "bucket", "before")
    return p.withColumn("page", F.expr(f"before div {page_bytes}L")).drop("before")


def page_table(paged: DataFrame) -> DataFrame:
    return paged.groupBy("page").agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))


def page_faults(hits: DataFrame, paged: DataFrame, batch: str) -> DataFrame:
    """batch, reads: distinct pages that each batch of queries (batch, bucket) touches, with an empty cache at its start."""
    return hits.join(paged.select("bucket", "page"), "bucket").groupBy(batch).agg(F.count_distinct("page").alias("reads"))


def lru_faults(pages: list[int], capacity: int) -> int:
    """Faults of a sequence of page reads with a least-recently-used cache; for traces on the driver."""
    cache: OrderedDict[int, None] = OrderedDict()
    faults = 0
    for p in pages:
        if p in cache:
            cache.move_to_end(p)
            continue
        faults += 1
        cache[p] = None
        if len(cache) > capacity:
            cache.popitem(last=False)
    return faults
