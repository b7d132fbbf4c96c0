"""N-gram Jaccard join by parity sketches, exact.

Each document's set of word shingles is hashed to a virtual bit sketch: a shingle flips one of 2**20 bits of one of m blocks. Equal
shingles cancel, so the Hamming distance of two sketches is a lower bound of their symmetric difference. For Jaccard >= t the
difference is at most (1-t)/(1+t) of the two sizes together, so two such documents agree in all but that many of the m blocks. Every size
band has its own m. A document need not emit all its blocks: under one global order of (block, content), more set bits first,
two documents that agree in all but d blocks agree in one of the first d+1 of each. Those blocks are the join keys.

Within a key no pairs are made: each member is tied to the key's first member in one of a few hashed orders; pairs whose folded
sketches are too far apart go, the rest are verified on the whole texts, and verified links are contracted to components. Keys whose other
members are then still in different components (keys of one first member together) are compared in blocks, fine sketch against fine sketch: first each member proposes its
nearest of another component, round after round while that finds links; then all that the sketches still allow across components is verified, so no link is lost.

Equal sets are one node throughout (`set_id`, a 64-bit hash of the set with its size), so groups of exact copies cost nothing.
Null or empty texts: no shingle, component of their own. Null ids: never linked, component null. Repeated rows: one node, all returned.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from . import common as C

BITS = 20
BLOCK_ROWS = 2000
#: Hashed orders that choose a key's first member; bits a shingle of the fine sketch; rounds of proposals.
ORDERS, FINE, ROUNDS = 8, 8, 5
REMEMBERED = 200_000


def shingles(h: np.ndarray, k: int) -> np.ndarray:
    """The distinct hashes of k consecutive words; of all words, if they are fewer."""
    if not len(h):
        return h
    w = min(k, len(h))
    s = np.zeros(len(h) - w + 1, np.uint64)
    for j in range(w):
        s += h[j : j + len(s)] * np.uint64(2 * j + 3) ^ (h[j : j + len(s)] >> np.uint64(17 + j))
    s = np.sort(C.mix(s, 100 + w))
    return s[np.concatenate(([True], s[1:] != s[:-1]))]


def sets(texts: pa.Array, k: int) -> Iterator[np.ndarray]:
    data, off = C.utf8(texts)
    for i, j in C.slices(off):
        h, at, _, _ = C.word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i])
        for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
            yield shingles(h[a:b], k)


def set_id(s: np.ndarray) -> int:
    return int(np.sum(C.mix(s, 3), dtype=np.uint64) ^ np.uint64(len(s))) - 2**63 if len(s) else 0


def folded(s: np.ndarray, each: int = 1) -> bytes:
    """The parity sketch of about `each` bits a shingle; a larger one folds to a smaller by XOR of its halves."""
    bits = max(64, each << int(len(s) - 1).bit_length())
    return np.packbits(np.bincount((C.mix(s, 5) & np.uint64(bits - 1)).astype(np.int64), minlength=bits).astype(np.uint8) & 1).tobytes()


def fold_to(x: np.ndarray, size: int) -> np.ndarray:
    while len(x) > size:
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    return x


class Plan:
    """Bands, blocks and prefix lengths for Jaccard >= num / den."""

    def __init__(self, num: int, den: int):
        self.num, self.den = num, den

    def apart(self, a: int, b: int) -> int:
        """The largest symmetric difference of linked sets of these sizes."""
        return (self.den - self.num) * (a + b) // (self.den + self.num)

    def bands(self, n: int) -> Iterator[tuple[int, int]]:
        """(band, emitted blocks): its own band, where it may be the smaller set, and those where it may be the larger."""
        own = int(n - 1).bit_length()
        yield own, self.apart(n, n * self.den // self.num) + 1
        for band in range(own - 1, -1, -1):
            if (1 << band) * self.den < n * self.num:
                break
            yield band, self.apart(n, 1 << band) + 1

    def blocks(self, band: int) -> int:
        u = 1 << band
        return int(1.25 * self.apart(u, u * self.den // self.num)) + 8

    def keys(self, s: np.ndarray) -> np.ndarray:
        out = []
        for band, p in self.bands(len(s)):
            m = self.blocks(band)
            x = C.mix(s, 11 + band)
            cell = np.sort((x % np.uint64(m)) << np.uint64(BITS) | (x >> np.uint64(44)))
            same = cell[1:] == cell[:-1]
            if same.any():  # two shingles on one bit cancel
                u, n = np.unique(cell, return_counts=True)
                cell = u[n % 2 == 1]
            block = cell >> np.uint64(BITS)
            at = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1]))) if len(cell) else np.zeros(0, np.int64)
            bits = np.diff(np.append(at, len(cell)))
            key = C.mix(np.add.reduceat(C.mix(cell, 13), at), 50 + band) if len(at) else np.zeros(0, np.uint64)
            if len(key) > p:
                key = key[np.lexsort((key, -bits))[:p]]
            elif len(key) < p:  # empty blocks come last in the order
                empty = np.sort(C.mix(np.setdiff1d(np.arange(m, dtype=np.uint64), block[at]), 1000 + band))
                key = np.concatenate((key, empty[: p - len(key)]))
            out.append(key)
        return np.concatenate(out).view(np.int64)

    def near(self, a: int, x: bytes, b: int, y: bytes) -> bool:
        if min(a, b) * self.den < max(a, b) * self.num:
            return False
        size = min(len(x), len(y))
        d = fold_to(np.frombuffer(x, np.uint8), size) ^ fold_to(np.frombuffer(y, np.uint8), size)
        return int(np.bitwise_count(d).sum()) <= self.apart(a, b)

    def linked(self, a: np.ndarray, b: np.ndarray) -> bool:
        both = len(np.intersect1d(a, b, assume_unique=True))
        return self.den * both >= self.num * (len(a) + len(b) - both)


def profiles(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, n, set_id and folded sketch of every row."""

    def run(batches):
        for x in C.freed(batches):
            n, ids, sk = [], [], []
            for s in sets(x.column(1), k):
                n.append(len(s))
                ids.append(set_id(s))
                sk.append(folded(s) if len(s) else None)
            yield C.batch_of({"doc_id": x.column(0), "n": pa.array(n, pa.int64()), "set_id": pa.array(ids, pa.int64()), "sketch": pa.array(sk, pa.binary())})

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n long, set_id long, sketch binary")


def block_keys(docs: DataFrame, k: int, plan: Plan) -> DataFrame:
    """(key, set_id) of the emitted blocks. A task emits a set it has just seen only once."""

    def run(batches):
        seen: set[int] = set()
        for x in C.freed(batches):
            ids, keys = [], []
            for s in sets(x.column(1), k):
                if not len(s):
                    continue
                sid = set_id(s)
                if sid in seen:
                    continue
                if len(seen) < REMEMBERED:
                    seen.add(sid)
                ids.append(sid)
                keys.append(plan.keys(s))
                if len(ids) == 500:
                    yield rows(ids, keys)
                    ids, keys = [], []
            if ids:
                yield rows(ids, keys)

    def rows(ids, keys):
        off = np.concatenate(([0], np.cumsum([len(x) for x in keys]))).astype(np.int32)
        return C.batch_of({"set_id": pa.array(ids, pa.int64()), "keys": pa.ListArray.from_arrays(pa.array(off), pa.array(np.concatenate(keys)))})

    return docs.where("doc_id is not null").select("doc_id", "text").mapInArrow(run, "set_id long, keys array<long>").select(F.explode("keys").alias("key"), "set_id")


def texts_of(sets_: DataFrame, nodes: DataFrame, docs: DataFrame) -> DataFrame:
    """(set_id, text) of stashed set ids. Text is moved only for the documents in question. A repeated id may give a row with another text."""
    need = C.stash(sets_.join(nodes.select("set_id", "rep"), "set_id").select("set_id", F.col("rep").alias("doc_id")), "need")
    return docs.select("doc_id", "text").join(C.maybe_broadcast(need, 40), "doc_id").select("set_id", "text")


def verified(pairs: DataFrame, nodes: DataFrame, docs: DataFrame, k: int, plan: Plan) -> DataFrame:
    """Of pairs (a, b) of set ids, those that the whole texts confirm."""
    texts = texts_of(pairs.select(F.col("a").alias("set_id")).unionByName(pairs.select(F.col("b").alias("set_id"))).distinct(), nodes, docs)

    def run(batches):
        for x in C.freed(batches):
            keep = []
            for s, t, i, j in zip(sets(x.column(2), k), sets(x.column(3), k), x.column(0).to_pylist(), x.column(1).to_pylist()):
                keep.append(set_id(s) == i and set_id(t) == j and plan.linked(s, t))
            yield C.batch_of({"a": x.column(0), "b": x.column(1)}).filter(pa.array(keep, pa.bool_()))

    both = pairs.select("a", "b").join(texts.select(F.col("set_id").alias("a"), F.col("text").alias("ta")), "a")
    both = both.join(texts.select(F.col("set_id").alias("b"), F.col("text").alias("tb")), "b").select("a", "b", "ta", "tb")
    return both.mapInArrow(run, "a long, b long")


def near_pairs(pairs: DataFrame, nodes: DataFrame, plan: Plan) -> DataFrame:
    """Of candidate pairs, those whose folded sketches allow a link, with the distance left to the bound."""

    def run(batches):
        for x in C.freed(batches):
            cols = [x.column(i).to_pylist() for i in range(2, 6)]
            keep = [plan.near(a, s, b, t) for a, s, b, t in zip(*cols)]
            yield C.batch_of({"a": x.column(0), "b": x.column(1)}).filter(pa.array(keep, pa.bool_()))

    p = pairs.join(nodes.select(F.col("set_id").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa")), "a")
    p = p.join(nodes.select(F.col("set_id").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb")), "b")
    return p.select("a", "b", "na", "sa", "nb", "sb").mapInArrow(run, "a long, b long")


def labelled(df: DataFrame, comps: DataFrame, *cols: str) -> DataFrame:
    for c in cols:
        df = df.join(comps.select(F.col("node").alias(c), F.col("comp").alias(f"c_{c}")), c, "left").withColumn(f"c_{c}", F.coalesce(f"c_{c}", c))
    return df


def open_ties(ties: DataFrame, comps: DataFrame) -> DataFrame:
    """The ties of those first members whose other members are in different components."""
    ends = labelled(ties, comps, "set_id")
    open_ = C.stash(ends.groupBy("pivot").agg(F.min("c_set_id").alias("x"), F.max("c_set_id").alias("y")).where("x != y").select("pivot"), "open")
    return C.stash(ties.join(C.maybe_broadcast(open_, 24), "pivot", "left_semi"), "rest")


def fine_sketches(rest: DataFrame, nodes: DataFrame, docs: DataFrame, k: int) -> DataFrame:
    def run(batches):
        for x in C.freed(batches):
            ids, n, sk = [], [], []
            for s, i in zip(sets(x.column(1), k), x.column(0).to_pylist()):
                if set_id(s) == i:
                    ids.append(i)
                    n.append(len(s))
                    sk.append(folded(s, FINE))
            yield C.batch_of({"set_id": pa.array(ids, pa.int64()), "n": pa.array(n, pa.int64()), "sketch": pa.array(sk, pa.binary())})

    found = texts_of(rest.select("set_id").distinct(), nodes, docs).mapInArrow(run, "set_id long, n long, sketch binary")
    return C.stash(found.dropDuplicates(["set_id"]), "fine")


def unresolved_pairs(rest: DataFrame, comps: DataFrame, fine: DataFrame, plan: Plan, nearest: bool) -> DataFrame:
    """Pairs of different components that are tied to one first member, as any two that share a key are, and that the fine sketches
    allow; of each member and tie only the nearest, if asked for."""
    s = C.stash(labelled(rest, comps, "set_id"), "labels")
    groups = s.groupBy("pivot").agg(F.min("c_set_id").alias("x"), F.max("c_set_id").alias("y"), F.count("*").alias("size")).where("x != y").select("pivot", "size")
    m = s.join(groups, "pivot").withColumn("block", F.floor((F.row_number().over(W.partitionBy("pivot").orderBy("set_id")) - 1) / BLOCK_ROWS).cast("int"))
    m = m.join(fine, "set_id")
    m = m.withColumn("other", F.explode(F.sequence(F.lit(0), F.floor((F.col("size") - 1) / BLOCK_ROWS).cast("int"))))
    m = m.select("pivot", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "set_id", F.col("c_set_id").alias("comp"), "n", "sketch")

    def run(g: pa.Table) -> pa.Table:
        n, comp, sid = (g.column(c).to_numpy() for c in ("n", "comp", "set_id"))
        sk = [np.frombuffer(x, np.uint8) for x in g.column("sketch").to_pylist()]
        size = min(map(len, sk))
        bits = np.stack([fold_to(x, size) for x in sk]).view(np.uint64)
        block = g.column("block").to_numpy()
        two = g.column("lo")[0].as_py() != g.column("hi")[0].as_py()
        a, b = [], []
        for i in range(len(n)):
            ok = (comp != comp[i]) & (np.minimum(n, n[i]) * plan.den >= np.maximum(n, n[i]) * plan.num)
            if two:
                ok &= block != block[i]
            if not nearest:
                ok[: i + 1] = False
            j = np.flatnonzero(ok)
            if len(j):
                room = (plan.den - plan.num) * (n[j] + n[i]) // (plan.den + plan.num) - np.bitwise_count(bits[j] ^ bits[i]).sum(1, dtype=np.int64)
                j = j[room >= 0] if not nearest else j[[room.argmax()]] if room.max() >= 0 else j[:0]
                a += [sid[i]] * len(j)
                b += sid[j].tolist()
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return m.groupBy("pivot", "lo", "hi").applyInArrow(run, "a long, b long").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def near_duplicates(docs: DataFrame, words: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """doc_id, n_shingles, set_id, component_id of every row of `docs` (doc_id, text): documents linked by Jaccard >= num / den, directly
    or through others, share the smallest doc_id as component_id."""
    spark = docs.sparkSession
    C.ship(spark)
    plan = Plan(num, den)
    docs = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    prof = C.stash(profiles(docs, words), "profiles")
    nodes = C.stash(prof.where("n > 0 and doc_id is not null").groupBy("set_id").agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), F.first("sketch").alias("sketch")), "nodes")
    w = W.partitionBy("key").orderBy(F.xxhash64("set_id", F.pmod("key", F.lit(ORDERS))), "set_id")
    stars = block_keys(docs, words, plan).withColumn("pivot", F.first("set_id").over(w.rowsBetween(W.unboundedPreceding, 0))).withColumn("before", F.lag("set_id").over(w))
    ties = C.stash(stars.where("before is not null and before != set_id").select("pivot", "set_id").distinct(), "ties")
    cand = C.stash(near_pairs(ties.select(F.col("pivot").alias("a"), F.col("set_id").alias("b")), nodes, plan), "cand")
    # one tie a set first; most others then lie within a component
    first = cand.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")
    links = C.stash(verified(first, nodes, docs, words, plan), "links")
    comps = C.stash(C.components(links), "comps")
    tested = cand.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()

    def confirm(pairs: DataFrame) -> bool:
        """Verifies pairs that were not tested yet; whether links were found."""
        nonlocal links, comps
        new = C.stash(verified(pairs, nodes, docs, words, plan), "found") if not pairs.isEmpty() else pairs
        if new.isEmpty():
            return False
        links = links.unionByName(new)
        comps = C.stash(C.components(links), "comps")
        return True

    confirm(C.stash(labelled(cand, comps, "a", "b").where("c_a != c_b").select("a", "b").join(first, ["a", "b"], "left_anti"), "more"))
    rest = open_ties(ties, comps)
    if not rest.isEmpty():
        fine = fine_sketches(rest, nodes, docs, words)
        more = True
        for nearest in [True] * ROUNDS + [False]:
            if nearest and not more:
                continue
            pairs = C.stash(unresolved_pairs(rest, comps, fine, plan, nearest).join(tested, ["a", "b"], "left_anti"), "pairs")
            tested = tested.unionByName(pairs)
            more = confirm(pairs)
    least = labelled(nodes.select("set_id", "rep"), comps, "set_id")
    least = least.join(least.groupBy("c_set_id").agg(F.min("rep").alias("component_id")), "c_set_id").select("set_id", "component_id")
    # a hot set (many exact copies) is on the large side of this join, where AQE can split it
    found = prof.select("doc_id", F.col("n").alias("n_shingles"), "set_id").join(least, "set_id", "left")
    return found.select("doc_id", "n_shingles", "set_id", F.when(F.col("n_shingles") == 0, F.col("doc_id")).when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def keep_one(docs: DataFrame, **how) -> DataFrame:
    """The documents without those whose component has a smaller id; of rows with one id, all stay."""
    found = near_duplicates(docs, **how).where("doc_id != component_id").select("doc_id").distinct()
    return docs.join(C.maybe_broadcast(C.stash(found, "drop"), 16), "doc_id", "left_anti").select(*docs.columns)
