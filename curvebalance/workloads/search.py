"""Point location and neighbours."""

from __future__ import annotations

from pyspark.sql import functions as F

from curvebalance.functions import curves, geometry
from curvebalance.operators import kdtree, knn, locate, metrics
from curvebalance.plans import tables
from curvebalance.plans.specs import TreeConfig

from . import points as P

QUERIES, ORACLE = {}, {}
BITS, B, K = 16, 32, 3


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


_H = P.HASH


def _queries(p):
    """A tenth of the points, by hash, and as many that are moved by a quarter of a cent and so miss."""
    hit = p.where(kdtree.hash_unit(F.col("uid")) % 10 == 0)
    return hit.select(F.col("uid").alias("qid"), "c0", "c1", "c2").unionByName(hit.select((-F.col("uid") - 1).alias("qid"), "c0", (F.col("c1") + 0.0025).alias("c1"), "c2"))


_LOC = f"SELECT uid AS qid, uid, true AS found FROM ({P.LINES_SQL}) WHERE {_H} % 10 = 0 UNION ALL SELECT -uid - 1, NULL, false FROM ({P.LINES_SQL}) WHERE {_H} % 10 = 0"


@query("locate_key", _LOC)
def _(spark, d):
    p = P.lineitem(spark, d)
    return locate.by_key(p, _queries(p), 3, bits=BITS, bucket_size=B)


@query("locate_tree", _LOC)
def _(spark, d):
    p = P.lineitem(spark, d)
    box = geometry.bounding_box(p, 3)
    q = _queries(p)
    unit = q.select("qid", *[geometry.scaled(F.col(f"c{i}"), *box[i]).alias(f"c{i}") for i in range(3)])
    tree = kdtree.build(tables.snapshot(geometry.unit_scale(p, 3, box), "unit"), 3, TreeConfig.of("median_sort"))
    return locate.by_tree(tree, unit)


@query("locate_join", _LOC)
def _(spark, d):
    p = P.lineitem(spark, d)
    return locate.by_join(p, _queries(p), 3)


@query("locate_stats", f"SELECT found, count(*) AS n FROM ({_LOC}) GROUP BY 1")
def _(spark, d):
    p = P.lineitem(spark, d)
    return locate.by_key(p, _queries(p), 3, bits=BITS, bucket_size=B).groupBy("found").agg(F.count("*").alias("n"))


_BUCKETS = f"SELECT uid, c0, c1, c2, rank // {B} AS bucket FROM {P.prefix_sql(P.keyed_sql(P.LINES_SQL, 3, BITS))}"
_D2 = "(q.c0 - p.c0) * (q.c0 - p.c0) + (q.c1 - p.c1) * (q.c1 - p.c1) + (q.c2 - p.c2) * (q.c2 - p.c2)"
_Q = f"{_H} % 64 = 5"


def _curve_sql(c: int) -> str:
    return f"SELECT qid, rn, uid, round(d2, 12) AS d2 FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, uid) AS rn FROM (SELECT q.uid AS qid, p.uid, {_D2} AS d2 FROM (SELECT * FROM pts WHERE {_Q}) q JOIN pts p ON p.bucket BETWEEN q.bucket - {c} AND q.bucket + {c})) WHERE rn <= {K}"


_EXACT = f"SELECT qid, rn, uid, round(d2, 12) AS d2 FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, uid) AS rn FROM (SELECT q.uid AS qid, p.uid, {_D2} AS d2 FROM (SELECT * FROM pts WHERE {_Q}) q, pts p)) WHERE rn <= {K}"


def _bucketed(spark, d):
    p = P.unit(P.lineitem(spark, d), 3)
    k = knn.buckets(curves.keyed(p, 3, BITS, box=[(0.0, 1.0)] * 3), B)
    return tables.snapshot(k.select("uid", "c0", "c1", "c2", "w", "rank", "bucket"), "bucketed")


def _asked(k):
    return k.where(kdtree.hash_unit(F.col("uid")) % 64 == 5).withColumnRenamed("uid", "qid")


@query("knn_curve", f"WITH pts AS ({_BUCKETS}) {_curve_sql(1)}")
def _(spark, d):
    k = _bucketed(spark, d)
    return knn.by_curve(k, _asked(k).select("qid", "c0", "c1", "c2", "bucket"), 3, K)


@query("knn_exact", f"WITH pts AS ({_BUCKETS}) {_EXACT}")
def _(spark, d):
    p = P.unit(P.lineitem(spark, d), 3)
    return knn.exact(p, _asked(p), 3, K)


def _recall_sql(c: int) -> str:
    return f"a{c} AS ({_curve_sql(c)})"


@query("knn_recall", f"WITH pts AS ({_BUCKETS}), e AS ({_EXACT}), " + ", ".join(map(_recall_sql, (0, 1, 2))) + " " + " UNION ALL ".join(f"SELECT {c} AS cutoff, {K} AS k, (SELECT round(avg(CASE WHEN a.uid IS NULL THEN 0.0::DOUBLE ELSE 1.0::DOUBLE END), 6) FROM e LEFT JOIN a{c} a USING (qid, uid)) AS recall" for c in (0, 1, 2)))
def _(spark, d):
    """Recall rises with the number of buckets searched on each side."""
    k = _bucketed(spark, d)
    q = tables.snapshot(_asked(k).select("qid", "c0", "c1", "c2", "bucket"), "queries")
    near = tables.snapshot(knn.by_curves(k, q, 3, K, (0, 1, 2)), "near")
    e = tables.snapshot(knn.exact(P.unit(P.lineitem(spark, d), 3), q, 3, K), "exact")
    out = None
    for c in (0, 1, 2):
        r = metrics.knn_recall(near.where(F.col("cutoff") == c), e, K).select(F.lit(c).alias("cutoff"), "k", "recall")
        out = r if out is None else out.unionByName(r)
    return out


@query("knn_rank_window", f"WITH pts AS (SELECT uid, c0, c1, c2, rank FROM {P.prefix_sql(P.keyed_sql(P.LINES_SQL, 3, BITS))}) SELECT qid, rn, uid, round(d2, 12) AS d2 FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, uid) AS rn FROM (SELECT q.uid AS qid, p.uid, {_D2} AS d2 FROM (SELECT * FROM pts WHERE {_Q}) q JOIN pts p ON p.rank BETWEEN q.rank - 100 AND q.rank + 100)) WHERE rn <= {K}")
def _(spark, d):
    k = _bucketed(spark, d)
    return knn.by_rank_window(k, _asked(k).select("qid", "c0", "c1", "c2", "rank"), 3, K, 100)


@query("knn_subtree", f"WITH pts AS (SELECT * FROM {P.unit_sql(P.LINES_SQL, 3)}) SELECT qid, rn, uid, round(d2, 12) AS d2 FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, uid) AS rn FROM (SELECT q.uid AS qid, p.uid, {_D2} AS d2 FROM (SELECT * FROM pts WHERE {_Q}) q, pts p) WHERE d2 <= 0.05::DOUBLE * 0.05::DOUBLE) WHERE rn <= {K}")
def _(spark, d):
    p = P.unit(P.lineitem(spark, d), 3)
    tree = kdtree.build(p, 3, TreeConfig.of("midpoint"))
    q = p.where(kdtree.hash_unit(F.col("uid")) % 64 == 5).withColumnRenamed("uid", "qid")
    return knn.by_subtree(tree, q, K, 0.05)
