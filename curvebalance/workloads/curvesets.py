"""Keys, order, prefix ranks and slices."""

from __future__ import annotations

from pyspark.sql import functions as F

from curvebalance.functions import curves, geometry
from curvebalance.operators import balance, knn, metrics, migrate, slicing
from curvebalance.plans import tables
from curvebalance.sources import datagen, io

from . import points as P

BITS, PARTS = 16, 16
QUERIES, ORACLE = {}, {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


@query("morton_orders", f"SELECT uid, key FROM {P.keyed_sql(P.ORDERS_SQL, 2, BITS)}")
def _(spark, d):
    return curves.keyed(P.orders(spark, d), 2, BITS).select("uid", "key")


@query("morton_lineitem", f"SELECT uid, key FROM {P.keyed_sql(P.LINES_SQL, 3, BITS)}")
def _(spark, d):
    return curves.keyed(P.lineitem(spark, d), 3, BITS).select("uid", "key")


@query("morton_events", f"SELECT uid, key FROM {P.keyed_sql(P.EVENTS_SQL, 3, BITS)}")
def _(spark, d):
    return curves.keyed(P.events(spark, d), 3, BITS).select("uid", "key")


@query("morton_10d", f"SELECT uid, key FROM {P.keyed_sql(P.LINES10_SQL, 10, 6)}")
def _(spark, d):
    return curves.keyed(P.lineitem10(spark, d), 10, 6).select("uid", "key")


_gray = "key"
for _s in range(1, 2 * BITS):
    _gray = f"xor({_gray}, key >> {_s})"


@query("gray_orders", f"SELECT uid, {_gray} AS key FROM {P.keyed_sql(P.ORDERS_SQL, 2, BITS)}")
def _(spark, d):
    return curves.keyed(P.orders(spark, d), 2, BITS, "gray").select("uid", "key")


_N = (1 << BITS) - 1


@query("hilbert_orders_2d", f"""
WITH RECURSIVE h(uid, x, y, s, key) AS (
  SELECT uid, q0, q1, {1 << BITS - 1}::BIGINT, 0::BIGINT FROM {P.cells_sql(P.ORDERS_SQL, 2, BITS)}
  UNION ALL
  SELECT uid,
    CASE WHEN (y & s) = 0 THEN (CASE WHEN (x & s) > 0 THEN {_N} - y ELSE y END) ELSE x END,
    CASE WHEN (y & s) = 0 THEN (CASE WHEN (x & s) > 0 THEN {_N} - x ELSE x END) ELSE y END,
    s >> 1, key + s * s * (CASE WHEN (x & s) > 0 THEN (CASE WHEN (y & s) > 0 THEN 2 ELSE 3 END) ELSE (CASE WHEN (y & s) > 0 THEN 1 ELSE 0 END) END)
  FROM h WHERE s > 0
) SELECT uid, key FROM h WHERE s = 0""")
def _(spark, d):
    return curves.keyed(P.orders(spark, d), 2, BITS, "hilbert").select("uid", "key")


@query("hilbert_lineitem_3d", f"SELECT uid, key FROM {P.hilbert3_sql(P.cells_sql(P.LINES_SQL, 3, BITS), BITS)}")
def _(spark, d):
    return curves.keyed(P.lineitem(spark, d), 3, BITS, "hilbert").select("uid", "key")


def _on_hilbert(bits: int) -> str:
    return f"(SELECT q0, q1, q2, key FROM {P.cell_mesh_sql(bits)} JOIN {P.hilbert3_sql(P.cell_mesh_sql(bits), bits)} USING (uid))"


@query("hilbert_mesh", P.steps_sql(_on_hilbert(5)))
def _(spark, d):
    """Steps of the Hilbert curve over the cells of a 32**3 mesh that hold line items. One range, so all steps are counted."""
    g = P.cell_mesh(spark, d, 5)
    k = g.withColumn("key", curves.hilbert_key([F.col(f"g{i}") for i in range(3)], 5)).withColumn("range", F.lit(0))
    return metrics.curve_steps(k, 3)


@query("curve_steps", """
WITH cells AS (SELECT q0, q1, q2 FROM """ + P.cell_mesh_sql(4) + """),
keyed AS (SELECT *, """ + P.morton_expr(3, 4) + """ AS key FROM cells),
steps AS (SELECT abs(q0 - lag(q0) OVER w) + abs(q1 - lag(q1) OVER w) + abs(q2 - lag(q2) OVER w) AS step FROM keyed WINDOW w AS (ORDER BY key))
SELECT 'morton' AS curve, count(*) AS steps, round(avg(CASE WHEN step = 1 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS unit_share, round(avg(step::DOUBLE), 6) AS mean_step FROM steps WHERE step IS NOT NULL
UNION ALL SELECT 'hilbert', * FROM (""" + P.steps_sql(_on_hilbert(4)) + ")")
def _(spark, d):
    g = tables.snapshot(P.cell_mesh(spark, d, 4), "mesh")
    cells = [F.col(f"g{i}") for i in range(3)]
    out = [metrics.curve_steps(g.withColumn("key", curves.key_of(cells, 4, c)).withColumn("range", F.lit(0)), 3).select(F.lit(c).alias("curve"), "steps", "unit_share", "mean_step") for c in ("morton", "hilbert")]
    return out[0].unionByName(out[1])


@query("morton_inverse", f"SELECT uid, q0 AS g0, q1 AS g1 FROM {P.cells_sql(P.ORDERS_SQL, 2, BITS)}")
def _(spark, d):
    k = curves.keyed(P.orders(spark, d), 2, BITS)
    a, b = curves.morton_cell(F.col("key"), 2, BITS)
    return k.select("uid", a.alias("g0"), b.alias("g1"))


@query("gray_inverse", f"SELECT uid, q0 AS g0, q1 AS g1 FROM {P.cells_sql(P.ORDERS_SQL, 2, BITS)}")
def _(spark, d):
    a, b = curves.gray_cell(F.col("key"), 2, BITS)
    return curves.keyed(P.orders(spark, d), 2, BITS, "gray").select("uid", a.alias("g0"), b.alias("g1"))


@query("hilbert_inverse", f"SELECT uid, q0 AS g0, q1 AS g1, q2 AS g2 FROM {P.cells_sql(P.LINES_SQL, 3, BITS)}")
def _(spark, d):
    g = curves.hilbert_cell(F.col("key"), 3, BITS)
    return curves.keyed(P.lineitem(spark, d), 3, BITS, "hilbert").select("uid", *[c.alias(f"g{i}") for i, c in enumerate(g)])


@query("hilbert_inverse_2d", f"SELECT uid, q0 AS g0, q1 AS g1 FROM {P.cells_sql(P.ORDERS_SQL, 2, BITS)}")
def _(spark, d):
    a, b = curves.hilbert_cell(F.col("key"), 2, BITS)
    return curves.keyed(P.orders(spark, d), 2, BITS, "hilbert").select("uid", a.alias("g0"), b.alias("g1"))


_ORD = P.prefix_sql(P.keyed_sql(P.ORDERS_LINES_SQL, 2, BITS))


@query("prefix_orders", f"SELECT uid, key, prefix FROM {_ORD}")
def _(spark, d):
    k = curves.keyed(P.orders_by_lines(spark, d), 2, BITS)
    return slicing.slice_curve(k, PARTS).select("uid", "key", F.col("prefix").cast("long").alias("prefix"))


@query("rank_orders", f"SELECT uid, key, rank FROM {_ORD}")
def _(spark, d):
    return slicing.order_points(curves.keyed(P.orders_by_lines(spark, d), 2, BITS))


@query("slices_orders", f"SELECT uid, {P.part_expr(PARTS)} AS part FROM {_ORD}")
def _(spark, d):
    return slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS).select("uid", "part")


@query("slices_midweight", f"SELECT uid, CAST(LEAST({PARTS - 1}, ((2 * prefix + w) * {PARTS}) // (2 * total)) AS INTEGER) AS part FROM {_ORD}")
def _(spark, d):
    return slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS, "midweight").select("uid", "part")


_LOADS = f"SELECT p.part, count(uid) AS n, CAST(coalesce(sum(w), 0) AS BIGINT) AS w FROM (SELECT CAST(i AS INTEGER) AS part FROM range({PARTS}) t(i)) p LEFT JOIN (SELECT uid, w, {P.part_expr(PARTS)} AS part FROM {_ORD}) s ON s.part = p.part GROUP BY p.part"


@query("slice_loads", _LOADS)
def _(spark, d):
    return slicing.loads(slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS), PARTS)


@query("imbalance_orders", f"SELECT CAST(floor(sum(w) / {PARTS}) AS BIGINT) AS avg_load, max(w) AS max_load, min(w) AS min_load, max(w) - min(w) AS imbalance FROM ({_LOADS})")
def _(spark, d):
    return metrics.load(slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS), PARTS)


@query("slices_refined", f"SELECT count(*) AS points, true AS within FROM ({P.ORDERS_SQL})")
def _(spark, d):
    """Whether refined slices differ by the heaviest point at most."""
    k = tables.snapshot(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), "keyed")
    s = slicing.slice_curve(k, PARTS, "refined")
    m = metrics.load(s, PARTS).crossJoin(s.agg(F.max("w").alias("heavy"), F.count("*").alias("points")))
    return m.select("points", (F.col("imbalance") <= F.col("heavy")).alias("within"))


@query("slices_close", f"""
WITH RECURSIVE o AS (SELECT uid, w, prefix, total FROM {_ORD}),
cuts(i, start) AS (
  SELECT 0, 0::BIGINT
  UNION ALL
  SELECT i + 1, CASE WHEN up - goal <= goal - down OR down <= start THEN up ELSE down END
  FROM (SELECT i, start, goal, (SELECT min(prefix + w) FROM o WHERE prefix + w >= goal) AS up, (SELECT max(prefix) FROM o WHERE prefix <= goal AND prefix >= start) AS down
        FROM (SELECT i, start, start + (SELECT max(total) - start FROM o)::DOUBLE / ({PARTS} - i) AS goal FROM cuts WHERE i < {PARTS - 1})))
SELECT CAST(p AS INTEGER) AS part, count(uid) AS n, CAST(coalesce(sum(w), 0) AS BIGINT) AS w FROM range({PARTS}) t(p)
LEFT JOIN (SELECT uid, w, (SELECT count(*) FROM cuts WHERE i > 0 AND start <= o.prefix) AS part FROM o) s ON s.part = p GROUP BY p""")
def _(spark, d):
    return slicing.loads(slicing.slice_curve(tables.snapshot(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), "keyed"), PARTS, "close"), PARTS)


@query("partition_check", f"SELECT (SELECT max(c) = 1 FROM (SELECT count(*) AS c FROM {_ORD} GROUP BY uid)) AS disjoint, (SELECT min(part) >= 0 AND max(part) < {PARTS} FROM (SELECT {P.part_expr(PARTS)} AS part FROM {_ORD})) AS in_range, (SELECT max(w) - min(w) FROM ({_LOADS})) <= (SELECT max(w) FROM ({P.ORDERS_LINES_SQL})) AS balanced")
def _(spark, d):
    return metrics.check_partition(slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS), PARTS)


_LINES = P.prefix_sql(P.keyed_sql(P.LINES_W_SQL, 3, BITS))


@query("full_balance_lineitem", f"SELECT part, count(*) AS n, CAST(sum(w) AS BIGINT) AS w, min(key) AS key_lo, max(key) AS key_hi FROM (SELECT *, {P.part_expr(PARTS)} AS part FROM {_LINES}) GROUP BY part")
def _(spark, d):
    return slicing.slice_table(balance.full(P.lineitem_weighted(spark, d), 3, PARTS).assigned)


_MOVES = f"SELECT CAST(uid % {PARTS} AS INTEGER) AS src, {P.part_expr(PARTS)} AS dst FROM {_LINES}"


def _transfers(spark, d):
    after = balance.full(P.lineitem_weighted(spark, d), 3, PARTS).assigned
    before = after.select("uid", F.pmod("uid", F.lit(PARTS)).cast("int").alias("part"))
    return migrate.plan(before, after)


@query("transfer_matrix", f"SELECT src, dst, count(*) AS n FROM ({_MOVES}) WHERE src <> dst GROUP BY src, dst")
def _(spark, d):
    return _transfers(spark, d).select("src", "dst", "n")


@query("transfer_rounds", f"SELECT src, dst, r AS round, LEAST(64, n - r * 64) AS n FROM (SELECT src, dst, count(*) AS n FROM ({_MOVES}) WHERE src <> dst GROUP BY src, dst), range(0, 100000) t(r) WHERE r * 64 < n")
def _(spark, d):
    return migrate.rounds(_transfers(spark, d), 4096)


@query("transfer_row_rounds", f"SELECT src, dst, r AS round, LEAST(64, n - r * 64) AS n FROM (SELECT src, dst, count(*) AS n FROM ({_MOVES}) WHERE src <> dst GROUP BY src, dst), range(0, 100000) t(r) WHERE r * 64 < n")
def _(spark, d):
    """The round of every moving row, counted."""
    after = balance.full(P.lineitem_weighted(spark, d), 3, PARTS).assigned
    rows = after.select("uid", F.pmod("uid", F.lit(PARTS)).cast("int").alias("src"), F.col("part").alias("dst"), F.lit(64).cast("long").alias("bytes")).where("src != dst")
    return migrate.row_rounds(rows, 4096).groupBy("src", "dst", "round").agg(F.count("*").alias("n"))


_PAYLOAD = f"SELECT o.uid, o.part, o.key, t.o_totalprice AS price FROM (SELECT *, {P.part_expr(PARTS)} AS part FROM {_ORD}) o JOIN orders t ON t.o_orderkey = o.uid"


def _payload(spark, d):
    return io.table(spark, d, "orders").select(F.col("o_orderkey").alias("uid"), F.col("o_totalprice").alias("price"))


@query("exchange_orders", f"SELECT uid, part, key, price FROM ({_PAYLOAD})")
def _(spark, d):
    """The payload in its slices: each row of orders with the part and key it is stored under."""
    s = slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS)
    return migrate.exchange(_payload(spark, d), tables.snapshot(s, "slices"), 2).select("uid", "part", "key", "price")


@query("reorder_orders", f"SELECT uid, price, rank FROM (SELECT o.uid, o.rank, t.o_totalprice AS price FROM {_ORD} o JOIN orders t ON t.o_orderkey = o.uid)")
def _(spark, d):
    """The payload in the order of the permutation."""
    order = tables.snapshot(slicing.order_points(curves.keyed(P.orders_by_lines(spark, d), 2, BITS)), "order")
    return migrate.reorder(_payload(spark, d), order).select("uid", "price", "rank")


_BUCKETS = P.prefix_sql(f"(SELECT min(uid) AS uid, key, count(*) AS n, CAST(sum(w) AS BIGINT) AS w FROM {P.keyed_sql(P.ORDERS_LINES_SQL, 2, 5)} GROUP BY key)")


@query("slices_of_buckets", f"SELECT key, n, w, {P.part_expr(PARTS)} AS part FROM {_BUCKETS}")
def _(spark, d):
    """Whole buckets (the cells of a coarse grid) are dealt to slices; none is cut."""
    k = tables.snapshot(curves.keyed(P.orders_by_lines(spark, d), 2, 5), "keyed")
    return slicing.slice_buckets(k, PARTS).select("key", "n", "w", "part")


@query("replicated_order", f"SELECT uid, key, rank FROM {P.prefix_sql(P.keyed_sql('SELECT uid * 4 + k AS uid, c0 + k * 1e-9::DOUBLE AS c0, c1 + k * 1e-9::DOUBLE AS c1, w FROM (' + P.ORDERS_SQL + '), range(4) t(k)', 2, BITS))}")
def _(spark, d):
    """The curve order of four copies of each point."""
    return slicing.order_points(curves.keyed(datagen.replicate(P.orders(spark, d), 4, 2), 2, BITS))


_SIZES = (1, 2, 4, 8, 16, 32, 64)


@query("scaling_model", f"WITH o AS {_ORD}, t AS (SELECT p AS size, max(w) AS time FROM (SELECT p, LEAST(p - 1, (prefix * p) // total) AS part, CAST(sum(w) AS BIGINT) AS w FROM o, (VALUES {', '.join(f'({p})' for p in _SIZES)}) s(p) GROUP BY 1, 2) GROUP BY 1) SELECT CAST(size AS INTEGER) AS size, time, round((SELECT time FROM t WHERE size = 1)::DOUBLE / time, 6) AS speedup FROM t")
def _(spark, d):
    """Strong scaling on the model clock: the time of a step on P parts is their heaviest load, and one part is the base."""
    k = tables.snapshot(slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), 1), "prefix")
    total = slicing.total_weight(k)
    t = None
    for p in _SIZES:
        one = k.withColumn("part", slicing.part_of(F.col("prefix"), total, p)).groupBy("part").agg(F.sum("w").alias("w")).agg(F.lit(p).alias("size"), F.max("w").alias("time"))
        t = one if t is None else t.unionByName(one)
    return metrics.speedup(t).select("size", "time", F.round("speedup", 6).alias("speedup"))


_SLICED = f"(SELECT *, {P.part_expr(PARTS)} AS part FROM {_ORD})"


@query("stored_in_order", f"SELECT uid, key, part FROM {_SLICED}")
def _(spark, d):
    """Slices written as files sorted by key, and read back."""
    path = tables.shared_path(spark, "sorted")
    io.write_sorted(slicing.slice_curve(curves.keyed(P.orders_by_lines(spark, d), 2, BITS), PARTS).select("uid", "key", "part"), path, "key", 4)
    return spark.read.parquet(path)


@query("distances", "SELECT uid, abs(c0) * 1.0::DOUBLE + abs(c1) * 1.0::DOUBLE AS l1, greatest(abs(c0), abs(c1)) AS linf, c0 * c0 * 2.0::DOUBLE + c1 * c1 * 0.5::DOUBLE AS weighted FROM (" + P.ORDERS_SQL + ")")
def _(spark, d):
    """Distances of orders from the origin."""
    a, o = [F.col("c0"), F.col("c1")], [F.lit(0.0), F.lit(0.0)]
    return P.orders(spark, d).select("uid", geometry.distance(a, o, "l1").alias("l1"), geometry.distance(a, o, "linf").alias("linf"), geometry.distance(a, o, "weighted", [2.0, 0.5]).alias("weighted"))


@query("neighbour_share", f"WITH a AS (SELECT uid, {P.part_expr(PARTS)} AS part FROM {P.prefix_sql(P.keyed_sql(P.ORDERS_SQL, 2, BITS))}), b AS (SELECT uid, {P.part_expr(PARTS)} AS part FROM {_ORD}) SELECT round(CAST(count(*) FILTER (abs(b.part - a.part) = 1) AS DOUBLE) / count(*), 6) AS share FROM a JOIN b USING (uid) WHERE a.part <> b.part")
def _(spark, d):
    m = balance.moved(*_two(spark, d)).where("step_size != 0")
    return m.agg(F.round(F.sum(F.when(F.abs("step_size") == 1, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("share"))


def _two(spark, d):
    """Orders cut with unit weights, and re-cut on the same curve with their numbers of line items."""
    before = balance.full(P.orders(spark, d), 2, PARTS)
    after = balance.incremental(before.assigned, P.orders_by_lines(spark, d), PARTS)
    return before.assigned, after.assigned


_TWO = f"a AS (SELECT uid, {P.part_expr(PARTS)} AS part FROM {P.prefix_sql(P.keyed_sql(P.ORDERS_SQL, 2, BITS))}), b AS (SELECT uid, {P.part_expr(PARTS)} AS part FROM {_ORD})"


@query("incremental_slices", f"WITH {_TWO} SELECT uid, a.part AS part_old, b.part AS part_new FROM a JOIN b USING (uid)")
def _(spark, d):
    a, b = _two(spark, d)
    return a.select("uid", F.col("part").alias("part_old")).join(b.select("uid", F.col("part").alias("part_new")), "uid")


@query("incremental_moves", f"WITH {_TWO} SELECT b.part - a.part AS step_size, count(*) AS n FROM a JOIN b USING (uid) GROUP BY 1")
def _(spark, d):
    return balance.moved(*_two(spark, d))


@query("surface_to_volume", f"""
WITH cells AS (SELECT uid, q0, q1, q2, CAST(1 AS BIGINT) AS w FROM {P.cell_mesh_sql(4)}),
keyed AS (SELECT *, {P.morton_expr(3, 4)} AS key FROM cells), parts AS (SELECT *, {P.part_expr(12)} AS part FROM {P.prefix_sql('keyed')}),
near AS (SELECT a.part AS own, b.part AS other FROM parts a CROSS JOIN (VALUES (1,0,0),(-1,0,0),(0,1,0),(0,-1,0),(0,0,1),(0,0,-1)) o(x,y,z)
  LEFT JOIN parts b ON b.q0 = a.q0 + x AND b.q1 = a.q1 + y AND b.q2 = a.q2 + z)
SELECT own AS part, (SELECT count(*) FROM parts p WHERE p.part = own) AS n, count(*) FILTER (other IS NULL OR other <> own) AS surface,
  count(*) FILTER (other IS NULL OR other <> own)::DOUBLE / (SELECT count(*) FROM parts p WHERE p.part = own) AS ratio FROM near GROUP BY own""")
def _(spark, d):
    g = tables.snapshot(P.cell_mesh(spark, d, 4), "mesh").withColumn("w", F.lit(1).cast("long"))
    k = g.withColumn("key", curves.interleave([F.col(f"g{i}") for i in range(3)], 4))
    return metrics.surface_to_volume(slicing.slice_curve(k, 12), 3)


@query("embed_customers", f"""
WITH seg AS (SELECT c_mktsegment, row_number() OVER (ORDER BY c_mktsegment) AS k FROM (SELECT DISTINCT c_mktsegment FROM customer)),
src AS (SELECT c_custkey AS uid, c_acctbal + 0.0::DOUBLE AS c0, CAST(c_nationkey AS DOUBLE) AS c1, CAST(k AS DOUBLE) AS c2, CAST(1 AS BIGINT) AS w FROM customer JOIN seg USING (c_mktsegment))
SELECT uid, key FROM {P.keyed_sql('SELECT * FROM src', 3, BITS)}""")
def _(spark, d):
    attrs = [geometry.AttrSpec("c_acctbal"), geometry.AttrSpec("c_nationkey"), geometry.AttrSpec("c_mktsegment", "category")]
    p = geometry.embed_attributes(io.table(spark, d, "customer"), "c_custkey", attrs)
    return curves.keyed(p, 3, BITS, box=[(0.0, 1.0)] * 3).select("uid", "key")


@query("box_query", """
SELECT CAST(b AS INTEGER) AS box_id, uid FROM (""" + P.ORDERS_SQL + """), (SELECT min(c0) AS a0, max(c0) AS z0, min(c1) AS a1, max(c1) AS z1 FROM (""" + P.ORDERS_SQL + """)), range(4) t(b)
WHERE c0 BETWEEN a0 + (z0 - a0) * (b * 0.2::DOUBLE) AND a0 + (z0 - a0) * (b * 0.2::DOUBLE + 0.25::DOUBLE)
  AND (b = 3 OR c1 BETWEEN a1 + (z1 - a1) * (b * 0.1::DOUBLE) AND a1 + (z1 - a1) * (b * 0.1::DOUBLE + 0.3::DOUBLE))""")
def _(spark, d):
    from curvebalance.operators import ranges

    p = P.orders(spark, d)
    box = geometry.bounding_box(p, 2)
    k = tables.snapshot(curves.keyed(p, 2, BITS, box=box), "keyed")  # the key is a column of the files, as ranges need
    (a0, z0), (a1, z1) = box
    boxes = {}
    for b in range(4):
        t = None if b == 3 else (a1 + (z1 - a1) * (b * 0.1), a1 + (z1 - a1) * (b * 0.1 + 0.3))
        boxes[b] = ([a0 + (z0 - a0) * (b * 0.2), t[0] if t else None], [a0 + (z0 - a0) * (b * 0.2 + 0.25), t[1] if t else None])
    return ranges.box_query(k, boxes, box, BITS)


@query("page_layout", f"SELECT CAST(before // 65536 AS BIGINT) AS page, CAST(sum(n) AS BIGINT) AS n, CAST(sum(bytes) AS BIGINT) AS bytes FROM (SELECT *, coalesce(sum(bytes) OVER (ORDER BY key_lo, bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM (SELECT rank // 32 AS bucket, min(key) AS key_lo, count(*) AS n, count(*) * 40 AS bytes FROM {P.prefix_sql(P.keyed_sql(P.LINES_SQL, 3, BITS))} GROUP BY 1)) GROUP BY 1")
def _(spark, d):
    from curvebalance.operators import external

    k = knn.buckets(curves.keyed(P.lineitem(spark, d), 3, BITS), 32)
    b = tables.snapshot(k.groupBy("bucket").agg(F.min("key").alias("key_lo"), F.count("*").alias("n")), "buckets")
    return external.page_table(external.paginate(b, 65536))


@query("page_cache")
def _(spark, d):
    """Page reads of every point, and faults behind a least-recently-used cache of 4 and of 64 pages. Points are dealt by hash to traces of about 5,000
    reads, as many as there are; each trace, in the order of the hash, has a cache of its own and is replayed in one task."""
    import pandas as pd

    from curvebalance.operators import external, kdtree

    tables.ship(spark)
    k = tables.snapshot(knn.buckets(curves.keyed(P.lineitem(spark, d), 3, BITS), 32), "bucketed")
    b = tables.snapshot(k.groupBy("bucket").agg(F.min("key").alias("key_lo"), F.count("*").alias("n")), "buckets")
    h = kdtree.hash_unit(F.col("uid"))
    traces = max(1, k.count() // 5000)
    reads = k.join(external.paginate(b, 65536).select("bucket", "page"), "bucket").select((h % traces).cast("long").alias("trace"), h.cast("long").alias("at"), "uid", "page")

    def run(g: pd.DataFrame) -> pd.DataFrame:
        pages = g.sort_values(["at", "uid"])["page"].tolist()
        return pd.DataFrame({"capacity": [4, 64], "reads": [len(pages)] * 2, "faults": [external.lru_faults(pages, c) for c in (4, 64)]})

    return reads.groupBy("trace").applyInPandas(run, "capacity int, reads long, faults long").groupBy("capacity").agg(F.sum("reads").alias("reads"), F.sum("faults").alias("faults"))


@query("page_faults", f"""
WITH k AS (SELECT *, rank // 32 AS bucket FROM {P.prefix_sql(P.keyed_sql(P.LINES_SQL, 3, BITS))}),
b AS (SELECT bucket, min(key) AS key_lo, count(*) * 40 AS bytes FROM k GROUP BY 1),
p AS (SELECT bucket, CAST(coalesce(sum(bytes) OVER (ORDER BY key_lo, bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // 65536 AS BIGINT) AS page FROM b)
SELECT {P.HASH} % 8 AS batch, count(DISTINCT page) AS reads FROM k JOIN p USING (bucket) WHERE {P.HASH} % 64 < 8 GROUP BY 1""")
def _(spark, d):
    from curvebalance.operators import external, kdtree

    k = tables.snapshot(knn.buckets(curves.keyed(P.lineitem(spark, d), 3, BITS), 32), "bucketed")
    b = tables.snapshot(k.groupBy("bucket").agg(F.min("key").alias("key_lo"), F.count("*").alias("n")), "buckets")
    h = kdtree.hash_unit(F.col("uid"))
    hits = k.where(h % 64 < 8).select((h % 8).alias("batch"), "bucket")
    return external.page_faults(hits, external.paginate(b, 65536), "batch")
