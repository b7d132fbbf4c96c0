"""Shared helpers of the corpus operators: shared-folder tables, size-checked broadcasts, ranks, components, word hashes."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window as W, functions as F

#: A table is broadcast only when it has been counted and holds no more than this many bytes; above it, joins shuffle.
BROADCAST_BYTES = 24 << 20
#: Rows of an Arrow batch.
BATCH_ROWS = 1000
#: Text is hashed in slices of about this many bytes, so a worker's memory does not depend on the batch size.
SLICE_BYTES = 1 << 19

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends this package to the executors once per application, so that nothing relies on a shared source folder. Where Arrow batches have
    Spark's default of 10,000 rows, they get fewer: rows are whole texts here, and a batch is held several times over."""
    sc = spark.sparkContext
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    if sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    root = Path(__file__).resolve().parents[1]
    to = Path(tempfile.mkdtemp()) / f"{root.name}_{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(to, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(str(to))


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share; a temporary one only where the session names none and all run on one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "curvebalance-shared")
    return base.rstrip("/") + "/llm"


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stash(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Writes a table to the shared folder and reads it back: lineage ends there and a lost executor loses nothing."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes the files of a stashed table that nothing reads any more (through Hadoop's file system, as they were written)."""
    spark = df.sparkSession
    jvm = spark._jvm
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/llm/" in path:
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def apart(df: DataFrame, used: tuple[str, ...]) -> tuple[DataFrame, dict[str, str]]:
    """Gives all columns but the used ones private names, so none clashes with an operator's; and the names by which `restored` undoes it."""
    names = {c: c if c in used else f"_own{i}" for i, c in enumerate(df.columns)}
    return df.toDF(*names.values()), {v: k for k, v in names.items()}


def restored(df: DataFrame, names: dict[str, str]) -> DataFrame:
    """The columns that `apart` saw, in their order and under their names, and no others."""
    return df.select(*[F.col(v).alias(k) for v, k in names.items()])


def maybe_broadcast(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Marks a stashed table for broadcast after counting it; too large a table is left to a shuffled join."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df


def partitions(df: DataFrame, least: int = 1) -> int:
    return max(least, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")))


def ordered_buckets(df: DataFrame, col: str, n: int) -> DataFrame:
    """Adds `bucket`: contiguous ranges of a numeric column, cut at approximate quantiles; the cuts are a driver-side list of n."""
    q = [x for x in (df.approxQuantile(col, [i / n for i in range(1, n)], 0.2 / n) if n > 1 else [])]
    cuts = sorted(set(q))
    if not cuts:
        return df.withColumn("bucket", F.lit(0))
    arr = F.array(*[F.lit(float(c)) for c in cuts])
    # the number of cuts below the value: native and free of joins
    expr = F.size(F.filter(arr, lambda c: c < F.col(col).cast("double")))
    return df.withColumn("bucket", expr)


def hashed_sample(df: DataFrame, cols: list[str], limit: int) -> DataFrame:
    """About `limit` rows, never more, chosen by a hash of some columns; all rows, if there are no more than that. Nothing is sorted."""
    n = df.count()
    if n <= limit:
        return df
    return df.where(F.xxhash64(*cols) < int(-(2**63) + 0.95 * limit / n * 2**64)).limit(limit)


def exclusive_prefix(df: DataFrame, order: str, value: str, out: str, n: int = 64) -> DataFrame:
    """Adds the sum of `value` over all rows with a smaller `order` (unique, not null), in two levels: a small table of bucket
    sums gives offsets, a window inside each bucket the rest. No window spans the table."""
    b = ordered_buckets(df, order, n)
    sums = b.groupBy("bucket").agg(F.sum(value).alias("_s"))
    # at most n rows
    offs = sums.withColumn("_o", F.coalesce(F.sum("_s").over(W.orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("bucket", "_o")
    w = W.partitionBy("bucket").orderBy(order).rowsBetween(W.unboundedPreceding, -1)
    return b.join(F.broadcast(offs), "bucket").withColumn(out, (F.col("_o") + F.coalesce(F.sum(value).over(w), F.lit(0))).cast("long")).drop("bucket", "_o")


def components(edges: DataFrame, name: str = "cc", a: str = "a", b: str = "b") -> DataFrame:
    """Connected components (node, comp = smallest node) by alternating star contractions.

    Each round is one aggregate and one join; the rounds grow with the logarithm of a component's diameter. A node of very
    many edges is pre-aggregated before the shuffle, and its side of the join can be split by AQE.
    """
    e = stash(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u != v").distinct(), name)
    last = None
    while True:
        # every node's larger neighbours get its smallest neighbour, then its smaller ones do
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        big = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = big.groupBy("u").agg(F.min("v").alias("m"))
        small = big.join(low, "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).where("u != v").distinct()
        new = stash(small, name)
        state = tuple(new.agg(F.count("*"), F.sum(F.hash("u", "v").cast("long")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        discard(e)
        e = new
        if state == last:
            break
        last = state
    return e.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct())


# ---- words and hashes, over the bytes of an Arrow string column ----

_M1, _M2, _M3 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = (x + np.uint64((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & (2**64 - 1))).astype(np.uint64)
    x ^= x >> np.uint64(30)
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


_BYTE = mix(np.arange(256, dtype=np.uint64), 7)
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_pow = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    global _pow
    if len(_pow) < n:
        p = np.full(max(n, 4096), _M3 | np.uint64(1), np.uint64)
        p[0] = 1
        _pow = np.cumprod(p, dtype=np.uint64)
    return _pow


def utf8(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all values and the offsets of each; a null counts as empty."""
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    col = col.fill_null("") if col.null_count else col
    if not len(col):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    kind = np.int64 if pa.types.is_large_string(col.type) else np.int32
    off = np.frombuffer(col.buffers()[1], kind, len(col) + 1, col.offset * np.dtype(kind).itemsize).astype(np.int64)
    buf = col.buffers()[2]
    data = np.frombuffer(buf, np.uint8) if buf is not None and buf.size else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def slices(off: np.ndarray, most: int = SLICE_BYTES):
    """Index ranges of rows that hold about `most` bytes, one row at least."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = j


def word_hashes(data: np.ndarray, off: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """64-bit hashes of the words [^ \\t-\\r]+ of each value; with them where each value's words begin, and the words' bounds in bytes."""
    n = len(data)
    if not n:
        z = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64), z, z
    data = _LOWER[data] if lower else data
    word = ~_SPACE[data]
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1]
    last[:-1] &= ~word[1:]
    full = off[1:] > off[:-1]
    at, end = off[:-1][full], off[1:][full] - 1
    first[at] |= word[at]
    last[end] |= word[end]
    s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
    if not len(s):
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64), s, e
    lens = e - s
    begin = np.cumsum(lens) - lens
    v = _BYTE[data[word]]
    v *= _powers(int(lens.max()))[np.arange(len(v)) - np.repeat(begin, lens)]
    h = mix(np.add.reduceat(v, begin) + lens.astype(np.uint64) * _M2, 1)
    return h, np.searchsorted(s, off), s, e


def release() -> None:
    """Gives freed memory back to the system: workers are reused, and what one stage held would count against the next."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def freed(batches):
    """Arrow batches; after every eighth, and at the end, freed memory is released."""
    for i, x in enumerate(batches):
        yield x
        del x
        if i % 8 == 7:
            release()
    release()


def few(batches, rows: int = 500):
    """Arrow batches in slices of a few rows, so what is unpacked at a time is small."""
    for x in freed(batches):
        for i in range(0, len(x), rows):
            yield x.slice(i, rows)


def batch_of(columns: dict[str, pa.Array]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))
