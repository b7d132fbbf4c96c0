"""URL rules and exact membership by a cascade of Bloom filters.

A rule is an action, a host and a path prefix; it fits its host and all subdomains. Of the rules that fit, that with the longest host
and path wins. What the rules block, of all keys (host and path) in the corpus, is the list that the cascade encodes: level 1 holds the
listed keys, level 2 those other keys of the corpus that level 1 accepts, level 3 the listed keys that level 2 accepts, and so on until
no key is left. A key of that universe is listed exactly if the last level
that accepts it, after which one rejects it or none follows, is an odd one (counted from 1), so a lookup is exact and needs no join. A key is named by two
64-bit hashes. Keys are split by hash into shards of bounded size, each with its own small cascade, built in one task. Together they are
broadcast if their size allows; otherwise urls are brought to their shard.

Where pages are judged, the verdict is what the cascade says: listed is block, all else allow. The rules are consulted where the list is made and to
name the rule that fits.

Null urls, or urls without `://`, have empty host and path, fit no rule and are not listed. Repeated rows are judged alike.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from . import common as C

SHARD_KEYS = 100_000


@dataclass(frozen=True)
class Rule:
    action: str
    host: str
    path: str = "/"

    @classmethod
    def parse(cls, text: str) -> Rule:
        """`block example.com/en/`"""
        action, _, rest = text.partition(" ")
        host, _, path = rest.partition("/")
        if action not in ("allow", "block"):
            raise ValueError(f"unknown action: {action}")
        return cls(action, host, f"/{path}")

    @property
    def name(self) -> str:
        return self.host + self.path


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty if there is no `://`."""
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return F.coalesce(F.translate(host, upper, lower), F.lit("")), F.coalesce(path, F.lit(""))


def fitting(rules: list[Rule], host: Column, path: Column, what: str) -> Column:
    """The name or action of the longest rule that fits, else null. Rules of one length can't both fit unless they are the same."""
    out = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.name), len(r.host))):
        fits = ((host == r.host) | host.endswith(f".{r.host}")) & path.startswith(r.path)
        out = F.when(fits, F.lit(getattr(r, what))).otherwise(out)
    return out


class Cascade:
    """Levels of Bloom filters over key hashes (one or two 64-bit numbers a key). A key goes down as long as levels accept it; where it stops says whether it is listed."""

    def __init__(self, levels: list[tuple[int, int, bytes]]):
        self.levels = [(hashes, salt, np.frombuffer(b, np.uint8)) for hashes, salt, b in levels]

    @staticmethod
    def _at(keys: np.ndarray, bits: int, hashes: int, salt: int) -> np.ndarray:
        one, two = (keys[:, 0], keys[:, 1]) if keys.ndim > 1 else (keys, keys)
        a, b = C.mix(one, 2 * salt), C.mix(two, 2 * salt + 1) | np.uint64(1)
        return ((a[:, None] + np.arange(hashes, dtype=np.uint64) * b[:, None]) % np.uint64(bits)).astype(np.int64)

    @classmethod
    def build(cls, listed: np.ndarray, others: np.ndarray) -> Cascade:
        """Of distinct keys. The first level has few false positives for the number of other keys, later ones a half."""
        levels, inside, outside = [], listed, others
        while len(inside):
            rate = 0.5 if levels else min(0.5, max(1e-6, len(inside) * 0.7 / max(1, len(outside))))
            hashes = max(1, round(-np.log2(rate)))
            bits = max(64, int(np.ceil(len(inside) * hashes / np.log(2) / 8)) * 8)
            salt = len(levels) + 1
            flat = np.zeros(bits, np.uint8)
            flat[cls._at(inside, bits, hashes, salt).ravel()] = 1
            one = cls([(hashes, salt, np.packbits(flat).tobytes())])
            levels.append((hashes, salt, np.packbits(flat).tobytes()))
            inside, outside = outside[one._in(0, outside)], inside
        return cls(levels)

    def _in(self, level: int, keys: np.ndarray) -> np.ndarray:
        hashes, salt, b = self.levels[level]
        at = self._at(keys, len(b) * 8, hashes, salt)
        return ((b[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1).all(1)

    def has(self, keys: np.ndarray) -> np.ndarray:
        found, live = np.zeros(len(keys), bool), np.arange(len(keys))
        for i in range(len(self.levels)):
            live = live[self._in(i, keys[live])]
            found[live] = i % 2 == 0
        return found


def hashes_of(x) -> np.ndarray:
    return np.stack([x.column(c).to_numpy().view(np.uint64) for c in ("key", "key2")], 1)


def build(keys: DataFrame, shards: int) -> DataFrame:
    """The cascades of distinct keys (shard, key, key2, listed): shard, level, hashes, salt, bits."""

    def run(g: pa.Table) -> pa.Table:
        k, listed = hashes_of(g), g.column("listed").to_numpy()
        c = Cascade.build(k[listed], k[~listed])
        n = len(c.levels)
        return pa.table({"shard": pa.array([g.column("shard")[0].as_py()] * n, pa.int32()), "level": pa.array(range(n), pa.int32()), "hashes": pa.array([x[0] for x in c.levels], pa.int32()), "salt": pa.array([x[1] for x in c.levels], pa.int32()), "bits": pa.array([x[2].tobytes() for x in c.levels], pa.binary())})

    return keys.groupBy("shard").applyInArrow(run, "shard int, level int, hashes int, salt int, bits binary")


def judge(pages: DataFrame, rules: list[Rule], shard_keys: int = SHARD_KEYS, broadcast_bytes: int = C.BROADCAST_BYTES) -> DataFrame:
    """page_id, host, path, rule, listed (by the cascade) and verdict of every page (page_id, url)."""
    spark = pages.sparkSession
    C.ship(spark)
    host, path = host_and_path(F.col("url"))
    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string")).select("page_id", host.alias("host"), path.alias("path"))
    rows = rows.withColumn("rule", fitting(rules, F.col("host"), F.col("path"), "name"))
    rows = rows.withColumn("key", F.xxhash64("host", "path")).withColumn("key2", F.xxhash64(F.lit(1), "path", "host"))
    # equal keys are merged before the shuffle, so a hot host or url is a few rows
    keys = rows.groupBy("key", "key2").agg(F.first("host").alias("host"), F.first("path").alias("path"))
    keys = C.stash(keys.select("key", "key2", (F.coalesce(fitting(rules, F.col("host"), F.col("path"), "action"), F.lit("allow")) == "block").alias("listed")), "urls")
    shards = max(8, keys.count() // shard_keys + 1)
    shard = F.pmod(F.xxhash64("key"), F.lit(shards)).cast("int")
    levels = C.stash(build(keys.withColumn("shard", shard), shards), "cascade")
    total = levels.agg(F.sum(F.length("bits"))).first()[0] or 0
    rows = rows.withColumn("shard", shard)
    cols = ["page_id", "host", "path", "rule"]
    schema = "page_id long, host string, path string, rule string, listed boolean"

    def answer(x, found: np.ndarray):
        return {c: x.column(c) for c in cols} | {"listed": pa.array(found)}

    if total <= broadcast_bytes:
        table: dict[int, list] = {}
        for r in levels.orderBy("shard", "level").collect():
            table.setdefault(r["shard"], []).append((r["hashes"], r["salt"], bytes(r["bits"])))
        sent = spark.sparkContext.broadcast(table)

        def run(batches):
            at = {s: Cascade(v) for s, v in sent.value.items()}
            for x in batches:
                k, s = hashes_of(x), x.column("shard").to_numpy()
                found = np.zeros(len(k), bool)
                for i in np.unique(s):
                    if i in at:
                        found[s == i] = at[i].has(k[s == i])
                yield C.batch_of(answer(x, found))

        judged = rows.select(*cols, "key", "key2", "shard").mapInArrow(run, schema)
    else:
        # distinct keys are judged at their shard, then meet their rows again

        def at_shard(k: pa.Table, c: pa.Table) -> pa.Table:
            own = Cascade([tuple(r[n] for n in ("hashes", "salt", "bits")) for r in sorted(c.to_pylist(), key=lambda r: r["level"])])
            return pa.table({"key": k.column("key"), "key2": k.column("key2"), "listed": pa.array(own.has(hashes_of(k)))})

        near = keys.select("key", "key2", shard.alias("shard")).groupBy("shard").cogroup(levels.groupBy("shard"))
        judged = rows.join(C.stash(near.applyInArrow(at_shard, "key long, key2 long, listed boolean"), "listed"), ["key", "key2"]).select(*cols, "listed")
    return judged.select(*cols, "listed", F.when(F.col("listed"), "block").otherwise("allow").alias("verdict"))

