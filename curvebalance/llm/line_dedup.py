"""Line deduplication over a corpus, with an edit bound, by a deletion-neighbourhood join.

A line's words (lower-cased A-Z, split at white space) decide. An occurrence of a line goes if an earlier one, by (doc_id, line), has the same words
or, for lines of at least `near_words` words, words within one insertion, deletion or substitution. Lines of fewer than `least_words` words stay; the queries
take 1, so that blank lines alone do.

Equal lines are merged first, by a partial aggregate, so a common line is one row. Two lines within one edit share, by the pigeonhole
principle, their first or second half; lines that share neither half with another line go no further. The others emit their deletion
neighbourhood: the hash of the words, and of the words without the i-th, for every i. Equal variants with one i mean a
substitution there; a variant equal to a line means an insertion. Within such a bucket all members are one edit from its earliest, so
each is tied to that alone. Ties are verified on the words.

Null ids: their lines neither go nor make others go. Null texts stay null. Rows that repeat a doc_id have the same places, and so do not
remove each other's lines. An empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from . import common as C

LEAST_WORDS, NEAR_WORDS = 4, 10
_ODD = C._M3 | np.uint64(1)


def lines_of(data: np.ndarray, off: np.ndarray):
    """For each value: word hashes, the word where each line begins and ends, and the line's number (from 0) with them."""
    h, at, s, _ = C.word_hashes(data, off)
    breaks = np.flatnonzero(data == 10)
    for k in range(len(off) - 1):
        own = breaks[np.searchsorted(breaks, off[k]) : np.searchsorted(breaks, off[k + 1])]
        a, b = int(at[k]), int(at[k + 1])
        cuts = np.concatenate(([a], a + np.searchsorted(s[a:b], own), [b]))
        yield h, cuts


def sequence_hash(h: np.ndarray, power: np.ndarray) -> np.ndarray:
    """Prefix sums from which the hash of any run of words follows."""
    return np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * power[: len(h)], dtype=np.uint64)))


def _inverse(n: int) -> np.ndarray:
    p = np.full(max(1, n), pow(int(_ODD), -1, 2**64), np.uint64)
    p[0] = 1
    return np.cumprod(p, dtype=np.uint64)


def run_hash(p: np.ndarray, inv: np.ndarray, a: np.ndarray, b: np.ndarray, salt: int) -> np.ndarray:
    """Hashes of the runs of words [a, b), wherever they stand."""
    return C.mix((p[b] - p[a]) * inv[a] + (b - a).astype(np.uint64) * C._M2, salt)


def occurrences(docs: DataFrame, least: int, near: int) -> DataFrame:
    """doc_id, line, words and full (hash) of every line of at least `least` words, with the half hashes of those that may be near another."""

    def run(batches):
        for x in C.freed(batches):
            ids = x.column(0)
            data, off = C.utf8(x.column(1))
            for i, j in C.slices(off):
                part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
                doc, line, a, b, h = [], [], [], [], None
                for k, (h, cuts) in enumerate(lines_of(part, o)):
                    n = np.diff(cuts)
                    keep = np.flatnonzero(n >= least)
                    doc.append(np.full(len(keep), i + k))
                    line.append(keep)
                    a.append(cuts[keep])
                    b.append(cuts[keep + 1])
                doc, line, a, b = (np.concatenate(v).astype(np.int64) for v in (doc, line, a, b))
                if not len(doc):
                    continue
                p, inv = sequence_hash(h, C._powers(len(h))), _inverse(len(h) + 1)
                full, words = run_hash(p, inv, a, b, 20), b - a
                far = words >= near - 1
                a, b = a[far], b[far]
                n = b - a
                half, less = n // 2, (n - 1) // 2
                # the halves of a line of n words, and those that a line of n - 1 words would have
                keys = [run_hash(p, inv, a, a + half, 21), run_hash(p, inv, a + half, b, 22), run_hash(p, inv, a, a + less, 21), run_hash(p, inv, b - (n - 1 - less), b, 22)]
                tags = [n, n, n - 1, n - 1]
                halves = np.stack([C.mix(k + t.astype(np.uint64) * C._M1, 23) for k, t in zip(keys, tags)], 1).ravel()
                yield C.batch_of({"doc_id": ids.take(pa.array(doc)), "line": pa.array(line, pa.int32()), "words": pa.array(words, pa.int32()), "full": pa.array(full.view(np.int64)), "halves": pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(far) * 4)), pa.int32()), pa.array(halves.view(np.int64)))})

    return docs.where("doc_id is not null").select("doc_id", "text").mapInArrow(run, "doc_id long, line int, words int, full long, halves array<long>")


def variants(rows: DataFrame) -> DataFrame:
    """variant, at (-1: the line itself) and full of every line in (full, content)."""

    def run(batches):
        for x in C.freed(batches):
            data, off = C.utf8(x.column(1))
            for i, j in C.slices(off, 1 << 18):
                h, at, _, _ = C.word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i])
                p, inv = sequence_hash(h, C._powers(len(h))), _inverse(len(h) + 1)
                n = np.diff(at)
                begin = np.repeat(at[:-1], n)
                k = np.arange(len(h)) - begin  # the deleted word of each variant
                # words after the deleted one move up by one place
                left, right = p[begin + k] - p[begin], p[begin + np.repeat(n, n)] - p[begin + k + 1]
                v = C.mix(left * inv[begin] + right * inv[begin + 1] + (np.repeat(n, n) - 1).astype(np.uint64) * C._M2, 20)
                own = run_hash(p, inv, at[:-1], at[1:], 20)
                full = x.column(0).slice(i, j - i).to_numpy()
                yield C.batch_of({"variant": pa.array(np.concatenate((own, v)).view(np.int64)), "at": pa.array(np.concatenate((np.full(j - i, -1), k)), pa.int32()), "full": pa.array(np.concatenate((full, np.repeat(full, n))))})

    return rows.select("full", "content").mapInArrow(run, "variant long, at int, full long")


def within_one(a: list[str], b: list[str]) -> bool:
    """Whether two word lists are within one insertion, deletion or substitution."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    i = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return a[i + (len(a) == len(b)) :] == b[i + 1 :]


_UPPER = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})


def words_of(line: str) -> list[str]:
    return [w for w in line.translate(_UPPER).translate({9: " ", 10: " ", 11: " ", 12: " ", 13: " "}).split(" ") if w]


def near_lines(distinct: DataFrame, docs: DataFrame, near_words: int) -> DataFrame:
    """`full` of the distinct lines (full, first, words, halves) that are within one edit of a line whose first occurrence is earlier."""
    d = distinct.where(F.col("words") >= near_words - 1)
    keys = d.select("full", F.explode(F.array_distinct("halves")).alias("half"))
    shared = keys.groupBy("half").agg(F.min("full").alias("x"), F.max("full").alias("y")).where("x != y").select("half")
    cand = d.select("full", "first").join(keys.join(shared, "half").select("full").distinct(), "full")
    where = cand.groupBy(F.col("first.doc_id").alias("doc_id")).agg(F.collect_list(F.struct(F.col("first.line").alias("line"), "full")).alias("lines"))
    where = C.stash(where, "near-where")

    def fetch(batches):
        for x in C.freed(batches):
            full, content = [], []
            for text, wanted in zip(x.column(0).to_pylist(), x.column(1).to_pylist()):
                rows = (text or "").split("\n")
                for r in wanted:
                    if r["line"] < len(rows):  # a repeated id may carry another text
                        full.append(r["full"])
                        content.append(rows[r["line"]])
            yield C.batch_of({"full": pa.array(full, pa.int64()), "content": pa.array(content, pa.string())})

    got = docs.select("doc_id", "text").join(C.maybe_broadcast(where, 400), "doc_id").select("text", "lines").mapInArrow(fetch, "full long, content string")
    rows = C.stash(got.dropDuplicates(["full"]), "near-lines")
    order = C.stash(cand.select("full", "first"), "near-order")
    v = C.stash(variants(rows).join(order, "full"), "variants")
    # substitutions: equal variants without the same word, each tied to the earliest
    earliest = v.where("at >= 0").groupBy("variant", "at").agg(F.min(F.struct("first", "full")).alias("m"), F.max("full").alias("x"), F.min("full").alias("y")).where("x != y")
    earliest = C.maybe_broadcast(C.stash(earliest.select("variant", "at", F.col("m.full").alias("to")), "earliest"), 40)
    sub = v.where("at >= 0").join(earliest, ["variant", "at"]).where("full != to").select("full", "to")
    # insertions: a line equal to another's variant, either way round
    whole = v.where("at = -1").select("variant", F.col("full").alias("short"), F.col("first").alias("f"))
    long_ = v.where("at >= 0").select("variant", "full", "first").distinct()
    later = long_.join(whole, "variant").where("f < first and full != short").select("full", F.col("short").alias("to"))
    least = long_.groupBy("variant").agg(F.min(F.struct("first", "full")).alias("m"))
    sooner = whole.join(least, "variant").where("m.first < f and m.full != short").select(F.col("short").alias("full"), F.col("m.full").alias("to"))
    ties = sub.unionByName(later).unionByName(sooner).distinct()
    both = ties.join(rows.withColumnRenamed("content", "x"), "full").join(rows.select(F.col("full").alias("to"), F.col("content").alias("y")), "to").select("full", "x", "y")

    def check(batches):
        for b in batches:
            ok = []
            for x, y in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                p, q = words_of(x), words_of(y)
                ok.append(len(p) >= near_words and len(q) >= near_words and within_one(p, q))
            yield C.batch_of({"full": b.column(0)}).filter(pa.array(ok, pa.bool_()))

    return both.mapInArrow(check, "full long").distinct()


def dropped_lines(docs: DataFrame, least_words: int = LEAST_WORDS, near_words: int = NEAR_WORDS) -> DataFrame:
    """doc_id, line (from 0) of every occurrence that goes."""
    C.ship(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    occ = C.stash(occurrences(docs, least_words, near_words), "lines")
    distinct = occ.groupBy("full").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.count("*").alias("c"), F.first("words").alias("words"), F.first("halves").alias("halves"))
    distinct = C.stash(distinct, "distinct-lines")
    near = C.stash(near_lines(distinct, docs, near_words), "near")
    why = distinct.select("full", "first", "c").join(near.withColumn("near", F.lit(True)), "full", "left").where("c > 1 or near").select("full", "first", F.coalesce("near", F.lit(False)).alias("near"))
    return occ.select("doc_id", "line", "full").join(why, "full").where(F.col("near") | (F.struct("doc_id", "line") > F.col("first"))).select("doc_id", "line").distinct()


def dedup(docs: DataFrame, **how) -> DataFrame:
    """Rows of `docs` (doc_id, text and others) with the text that is left, n_lines and dropped (numbers of the lines that went)."""
    gone = dropped_lines(docs, **how).groupBy("doc_id").agg(F.collect_list("line").alias("dropped"))
    keep = [c for c in docs.columns if c not in ("dropped", "n_lines")]
    rows = docs.select(*keep).join(C.maybe_broadcast(C.stash(gone, "dropped"), 120), "doc_id", "left").select(*keep, "dropped")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name in keep) + ", n_lines int, dropped array<int>"

    def run(batches):
        for x in C.freed(batches):
            text, n, lists = [], [], []
            for t, gone_ in zip(x.column("text").to_pylist(), x.column("dropped").to_pylist()):
                rows_ = t.split("\n") if t is not None else []
                out = set(gone_ or ())
                n.append(len(rows_))
                lists.append(sorted(out))
                text.append(t if not out or t is None else "\n".join(r for i, r in enumerate(rows_) if i not in out))
            cols = {c: x.column(c) for c in keep} | {"text": pa.array(text, pa.string())}
            yield C.batch_of(cols | {"n_lines": pa.array(n, pa.int32()), "dropped": pa.array(lists, pa.list_(pa.int32()))})

    return rows.mapInArrow(run, schema)
