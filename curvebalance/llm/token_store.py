"""Content-addressed store of token ids.

Writing: every document's id stream is cut into chunks where a rolling hash of the last 16 ids says so, and each chunk is
named by its BLAKE2b digest. A chunk that occurs several times is kept by its first occurrence, by doc_id; all others refer to it.
  packs/     the id files, numbered (`part`) and filled in ascending doc_id order, null ids last. A row (`row` in its part) is one document: its
             recipe (chunks, in order, with whether their bytes are here or elsewhere), the bytes it keeps, and `place`, the ids before it in the part
  index/     where each document is: doc_id, copy, part, row, start, n_tokens and the Merkle root of its chunk digests
  manifest/  one row a part: its documents, ids, first id of the store, and the Merkle root of its documents
Reading: index and packs are held against the manifest first, so a row that is lost, doubled or altered is an error; `start` comes from the parts'
ids and the places in them. Documents that keep all their chunks are rebuilt where their row is read; only shared chunks are moved to those that refer
to them, a chunk that many refer to in several tasks. Each chunk's digest and each root is computed again from the bytes; a difference is an error.

Null or empty texts hold the end id alone. Rows that repeat a doc_id are stored as copies 0, 1, ... in the order of a hash of their texts; so are rows
with a null doc_id. Other columns are not stored. What reaches the driver is one row a part.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from . import common as C, tokens as T

LEAST, MOST, WINDOW_STEPS = 64, 4096, 4
#: A cut where this many leading bits of the rolling hash are zero: one in 512 ids.
CUT_BITS = 9
_GEAR = C.mix(np.arange(1 << 17, dtype=np.uint64), 77)


def candidates(ids: np.ndarray) -> np.ndarray:
    """Places where the rolling hash, which at i depends on the 16 ids up to i alone, asks for a cut; so equal passages are cut alike.

    Documents may stand one after another: no cut is taken within the first `LEAST` ids of one, and so none that saw ids of its predecessor.
    """
    h = _GEAR[ids.astype(np.uint32) & np.uint32(0x1FFFF)]
    for k in range(WINDOW_STEPS):
        step = 1 << k
        h[step:] = h[step:] + (h[:-step] << np.uint64(step))
    return np.flatnonzero(h >> np.uint64(64 - CUT_BITS) == 0) + 1


def cuts(ids: np.ndarray) -> list[int]:
    """Ends of the chunks of one document."""
    return bounded(candidates(ids).tolist(), len(ids))


def bounded(wanted: list[int], n: int) -> list[int]:
    """The wanted cuts of a document of n ids, so that chunks hold LEAST to MOST ids; the last may be shorter."""
    out, last = [], 0
    for c in wanted:
        while c - last > MOST:
            last += MOST
            out.append(last)
        if c - last >= LEAST:
            out.append(c)
            last = c
    while n - last > MOST:
        last += MOST
        out.append(last)
    return out + [n] * (last < n)


def digest(b: bytes) -> bytes:
    return hashlib.blake2b(b, digest_size=16).digest()


def merkle(leaves: list[bytes]) -> bytes:
    while len(leaves) > 1:
        leaves = [digest(b"".join(leaves[i : i + 2])) for i in range(0, len(leaves), 2)]
    return leaves[0] if leaves else digest(b"")


def encoded(docs: DataFrame, encoder: T.WordBpe, end_id: int) -> DataFrame:
    """`uid` names a row: once written, it stays."""

    def run(batches):
        kind = encoder.dtype()
        end = np.array([end_id], kind).tobytes()
        uid = TaskContext.get().partitionId() << 33
        for x in C.freed(batches):
            for at, texts in T.slices_of(x.column(1)):
                blobs, lens, names = [b + end for b in encoder.encode(texts)], [], []
                wanted = candidates(np.frombuffer(b"".join(blobs), kind))
                first = np.cumsum([0, *[len(b) // kind.itemsize for b in blobs]])
                split = np.searchsorted(wanted, first, "right")
                for i, b in enumerate(blobs):
                    e = bounded((wanted[split[i] : split[i + 1]] - first[i]).tolist(), len(b) // kind.itemsize)
                    lens.append(np.diff([0, *e]).tolist())
                    names.append([digest(b[s * kind.itemsize : t * kind.itemsize]) for s, t in zip([0, *e], e)])
                yield C.batch_of({"uid": pa.array(range(uid, uid + len(texts)), pa.int64()), "doc_id": x.column(0).slice(at, len(texts)), "hash": x.column(2).slice(at, len(texts)), "n_tokens": pa.array([len(b) // kind.itemsize for b in blobs], pa.int64()), "width": pa.array([kind.itemsize] * len(blobs), pa.int32()), "ids": pa.array(blobs, pa.binary()), "lens": pa.array(lens, pa.list_(pa.int32())), "digests": pa.array(names, pa.list_(pa.binary()))})
                uid += len(texts)

    return docs.mapInArrow(run, "uid long, doc_id long, hash long, n_tokens long, width int, ids binary, lens array<int>, digests array<binary>")


#: A digest with more references than this is dealt to several tasks; so many digests at most (a share of all references) are told to all tasks.
HOT, HOT_DIGESTS = 500, 100_000


def met(many: DataFrame, one: DataFrame, salt: Column) -> DataFrame:
    """Joins references (many rows a digest) with the rows of their digests (one each); a hot digest's row is repeated, its references are dealt."""
    counts = C.stash(many.groupBy("digest").agg(F.count("*").alias("n")).where(f"n > {HOT}"), "hot")
    total = counts.agg(F.sum("n")).first()[0] or 0
    hot = F.broadcast(counts.where(F.col("n") > max(HOT, total / HOT_DIGESTS)).select("digest", F.ceil(F.col("n") / HOT).cast("int").alias("parts")))
    many = many.join(hot, "digest", "left").withColumn("part_of", F.coalesce(F.pmod(salt, F.col("parts")), F.lit(0)).cast("int")).drop("parts")
    one = one.join(hot, "digest", "left").withColumn("part_of", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("parts"), F.lit(1)) - 1))).drop("parts")
    return many.join(one, ["digest", "part_of"]).drop("part_of")


RECIPE = "recipe array<struct<digest: binary, len: int, kept: boolean, shared: boolean>>"
PACK = f"part int, row long, place long, doc_id long, copy int, n_tokens long, width int, absent int, shared int, root binary, {RECIPE}, bytes binary"
SEAL = "part int, docs long, n_tokens long, gapless boolean, first long, last long, last_copies int, root binary"


def write(docs: DataFrame, path: str, vocabulary: str, end_id: int = 1) -> None:
    """Writes the store of all documents (doc_id, text) under `path`."""
    spark = docs.sparkSession
    C.ship(spark)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).withColumn("hash", F.xxhash64("text"))
    enc = C.stash(encoded(docs, T.WordBpe(vocabulary), end_id), "encoded", "lz4")
    occ = enc.select("uid", "doc_id", F.posexplode("digests").alias("seq", "digest"))
    # null ids come last, as they do in the files
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "uid", "seq")
    owner = C.stash(occ.groupBy("digest").agg(F.min(first).alias("own"), F.count("*").alias("c")).where("c > 1").select("digest", "own.uid", "own.seq").toDF("digest", "own_uid", "own_seq"), "owners")
    repeated = met(occ.select("uid", "seq", "digest").join(C.maybe_broadcast(owner.select("digest"), 40), "digest", "left_semi"), owner, F.xxhash64("uid", "seq"))
    here = (F.col("uid") == F.col("own_uid")) & (F.col("seq") == F.col("own_seq"))
    marks = C.stash(repeated.groupBy("uid").agg(F.collect_list(F.when(here, F.col("seq"))).alias("shared"), F.collect_list(F.when(~here, F.col("seq"))).alias("absent")), "marks")

    def run(batches):
        part, row, place, last, copy = TaskContext.get().partitionId(), 0, 0, None, 0
        for x in C.few(batches):
            cols = x.to_pydict()
            blobs, recipe, roots, counts, at = [], [], [], [], []
            for doc, n, b, w, lens, names, shared, absent in zip(*(cols[c] for c in ("doc_id", "n_tokens", "ids", "width", "lens", "digests", "shared", "absent"))):
                gone, lent = set(absent or ()), set(shared or ())
                e = np.cumsum([0, *lens]) * w
                blobs.append(b"".join(b[e[i] : e[i + 1]] for i in range(len(lens)) if i not in gone) if gone else b)
                recipe.append([{"digest": d, "len": k, "kept": i not in gone, "shared": i in lent} for i, (d, k) in enumerate(zip(names, lens))])
                roots.append(merkle(names))
                counts.append((len(gone), len(lent)))
                copy = copy + 1 if row and doc == last else 0
                at.append((row, place, copy))
                row, place, last = row + 1, place + n, doc
            kind = pa.list_(pa.struct([("digest", pa.binary()), ("len", pa.int32()), ("kept", pa.bool_()), ("shared", pa.bool_())]))
            yield C.batch_of({"part": pa.array([part] * len(x), pa.int32()), "row": pa.array([a[0] for a in at], pa.int64()), "place": pa.array([a[1] for a in at], pa.int64()), "doc_id": x.column("doc_id"), "copy": pa.array([a[2] for a in at], pa.int32()), "n_tokens": x.column("n_tokens"), "width": x.column("width"), "absent": pa.array([c[0] for c in counts], pa.int32()), "shared": pa.array([c[1] for c in counts], pa.int32()), "root": pa.array(roots, pa.binary()), "recipe": pa.array(recipe, kind), "bytes": pa.array(blobs, pa.binary())})

    order = [F.asc_nulls_last("doc_id"), F.asc("hash"), F.asc("uid")]
    full = enc.join(C.maybe_broadcast(marks, 80), "uid", "left").repartitionByRange(C.partitions(enc), *order).sortWithinPartitions(*order)
    full.select("doc_id", "n_tokens", "ids", "width", "lens", "digests", "shared", "absent").mapInArrow(run, PACK).write.option("compression", "zstd").parquet(f"{path}/packs")
    C.discard(enc)
    packs = spark.read.schema(PACK).parquet(f"{path}/packs")
    rows, start, carry, before = [], 0, 0, None
    for r in sealed(packs).orderBy("part").collect():  # one row a part
        carry = carry if before is not None and r["first"] == before["last"] else 0
        rows.append((r["part"], r["docs"], start, r["n_tokens"], r["first"], carry, bytes(r["root"])))
        carry, start, before = r["last_copies"] + (carry if r["first"] == r["last"] else 0), start + r["n_tokens"], r
    manifest = spark.createDataFrame(rows, "part int, docs long, start long, n_tokens long, first long, carry int, root binary")
    manifest.coalesce(1).write.parquet(f"{path}/manifest")
    located(spark, path, packs).select("doc_id", "copy", "part", "row", "start", "n_tokens", "root").write.parquet(f"{path}/index")


def located(spark: SparkSession, path: str, packs: DataFrame) -> DataFrame:
    """`start` and `copy` over the whole store, from what the manifest says of each part (rows of which are bounded by the number of files)."""
    parts = F.broadcast(spark.read.parquet(f"{path}/manifest").select("part", F.col("start").alias("first_start"), "first", "carry"))
    copy = (F.col("copy") + F.when(F.col("doc_id").eqNullSafe(F.col("first")), F.col("carry")).otherwise(0)).cast("int")
    return packs.join(parts, "part").withColumn("copy", copy).withColumn("start", F.col("first_start") + F.col("place")).drop("first_start", "first", "carry")


def sealed(rows: DataFrame, start: str = "place") -> DataFrame:
    """One row a part: documents, ids, whether they stand without gaps, first and last doc_id, and the Merkle root over the documents in order.
    A part is one file's documents, so the list that is gathered for it is bounded by a file."""

    def run(batches):
        for x in C.few(batches, 8):
            out = []
            for part, docs in zip(x.column("part").to_pylist(), x.column("docs").to_pylist()):
                base, at, gapless, leaves, copies = docs[0]["at"], docs[0]["at"], True, [], 0
                for i, d in enumerate(docs):
                    gapless &= d["row"] == i and d["at"] == at
                    at += d["n_tokens"]
                    copies = copies + 1 if i and docs[i - 1]["doc_id"] == d["doc_id"] else 1
                    leaves.append(digest(struct.pack("<?qq", d["doc_id"] is None, d["doc_id"] or 0, d["n_tokens"]) + d["root"]))
                out.append((part, len(docs), at - base, gapless, docs[0]["doc_id"], docs[-1]["doc_id"], copies, merkle(leaves)))
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield C.batch_of({f.split()[0]: pa.array(c, k) for f, c, k in zip(SEAL.split(", "), zip(*out), kinds)})

    doc = F.struct("row", F.col(start).alias("at"), "doc_id", "n_tokens", "root")
    return rows.groupBy("part").agg(F.sort_array(F.collect_list(doc)).alias("docs")).mapInArrow(run, SEAL)


def verify(spark: SparkSession, path: str) -> None:
    """Holds the rows of packs and index against the manifest."""
    parts = {r["part"]: r for r in spark.read.parquet(f"{path}/manifest").collect()}
    for name, at in (("packs", "place"), ("index", "start")):
        seen = sealed(spark.read.parquet(f"{path}/{name}").select("part", "row", at, "doc_id", "n_tokens", "root"), at).collect()
        good = len(seen) == len(parts) and all(r["gapless"] and r["part"] in parts and all(r[c] == parts[r["part"]][c] for c in ("docs", "n_tokens", "root")) for r in seen)
        if not good:
            raise ValueError(f"{name} and manifest differ")


def _rebuild(batches):
    """Checks every chunk and root; gives the whole ids. Fetched bytes, if any, come as (seq, bytes) in `got`."""
    for x in C.few(batches):
        cols = x.to_pydict()
        out = []
        for b, w, recipe, root, got in zip(cols["bytes"], cols["width"], cols["recipe"], cols["root"], cols.get("got") or [None] * len(x)):
            other, at, parts, names = {g["seq"]: g["bytes"] for g in got or ()}, 0, [], []
            for i, c in enumerate(recipe):
                if c["kept"]:
                    part = b[at : at + c["len"] * w]
                    at += len(part)
                elif i in other:
                    part = other[i]
                else:
                    raise ValueError("a chunk is missing")
                names.append(digest(part))
                if names[-1] != c["digest"]:
                    raise ValueError("a chunk differs from its digest")
                parts.append(part)
            if merkle(names) != root:
                raise ValueError("a document differs from its root")
            out.append(b"".join(parts))
        yield C.batch_of({c: x.column(c) for c in ("doc_id", "copy", "start", "width")} | {"ids": pa.array(out, pa.binary())})


def chunks(packs: DataFrame, shared_only: bool = True) -> DataFrame:
    """digest and bytes of the kept chunks, all or only those that others refer to."""

    def run(batches):
        for x in C.few(batches):
            names, parts = [], []
            for b, w, recipe in zip(*(x.column(c).to_pylist() for c in ("bytes", "width", "recipe"))):
                at = 0
                for c in recipe:
                    n = c["len"] * w * c["kept"]
                    if c["shared"] or c["kept"] and not shared_only:
                        names.append(c["digest"])
                        parts.append(b[at : at + n])
                    at += n
            yield C.batch_of({"digest": pa.array(names, pa.binary()), "bytes": pa.array(parts, pa.binary())})

    rows = packs.where("shared > 0") if shared_only else packs
    return rows.select("width", "recipe", "bytes").mapInArrow(run, "digest binary, bytes binary")


def fetch(spark: SparkSession, path: str, names: DataFrame) -> DataFrame:
    """digest and bytes of the chunks that `names` (digest) asks for."""
    C.ship(spark)
    return chunks(spark.read.schema(PACK).parquet(f"{path}/packs"), False).join(names.select("digest").distinct(), "digest", "left_semi")


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, copy, start, width (bytes an id) and ids of every document, rebuilt and verified."""
    C.ship(spark)
    verify(spark, path)
    packs = located(spark, path, spark.read.schema(PACK).parquet(f"{path}/packs"))
    part = packs.where("absent > 0")
    want = part.select("part", "row", F.posexplode("recipe").alias("seq", "c")).where("not c.kept").select("part", "row", "seq", F.col("c.digest").alias("digest"))
    got = met(want, chunks(packs), F.xxhash64("part", "row", "seq")).groupBy("part", "row").agg(F.collect_list(F.struct("seq", "bytes")).alias("got"))
    cols = ["doc_id", "copy", "start", "width", "recipe", "root", "bytes"]
    schema = "doc_id long, copy int, start long, width int, ids binary"
    whole = packs.where("absent = 0").select(*cols).mapInArrow(_rebuild, schema)
    return whole.unionByName(part.join(got, ["part", "row"], "left").select(*cols, "got").mapInArrow(_rebuild, schema))


def digests(ids: DataFrame) -> DataFrame:
    """doc_id, copy, start, n_tokens and the crc32 of the ids as unsigned 32-bit integers."""

    def run(batches):
        for x in C.few(batches):
            rows = list(zip(x.column("ids").to_pylist(), x.column("width").to_pylist()))
            crc = [zlib.crc32(np.frombuffer(b, f"<u{w}").astype("<u4").tobytes()) for b, w in rows]
            yield C.batch_of({c: x.column(c) for c in ("doc_id", "copy", "start")} | {"n_tokens": pa.array([len(b) // w for b, w in rows], pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})

    return ids.mapInArrow(run, "doc_id long, copy int, start long, n_tokens long, ids_crc32 long")
