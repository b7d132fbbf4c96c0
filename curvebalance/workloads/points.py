"""Point sets from the given tables, and the SQL that makes the same ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from curvebalance.functions import geometry
from curvebalance.plans.specs import PointSpec
from curvebalance.sources.io import table

#: First day of the day coordinates.
DAY0 = "1992-01-01"


def days(c: str):
    return F.datediff(F.col(c).cast("date"), F.lit(DAY0).cast("date"))


def orders(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "orders").select(F.col("o_orderkey"), (F.col("o_totalprice")).alias("p"), days("o_orderdate").alias("t"))
    return geometry.as_points(t, PointSpec("o_orderkey", ("p", "t")))


def orders_by_lines(spark: SparkSession, d: str) -> DataFrame:
    """Orders weighted by their number of line items (0, if they have none)."""
    n = table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("uid")).agg(F.count("*").alias("lines"))
    return orders(spark, d).join(n, "uid", "left").withColumn("w", F.coalesce("lines", F.lit(0)).cast("long")).drop("lines")


def line_id():
    return (F.round(F.col("l_extendedprice") * 100).cast("long") * 64 + F.col("l_quantity").cast("long")) * 4096 + days("l_shipdate")


def lineitem(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "lineitem").select(line_id().alias("uid"), F.col("l_quantity").alias("a"), F.col("l_extendedprice").alias("b"), days("l_shipdate").alias("t"), F.col("l_linenumber").cast("long").alias("w"))
    return geometry.as_points(t, PointSpec("uid", ("a", "b", "t")))


def lineitem_weighted(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "lineitem").select(line_id().alias("uid"), F.col("l_quantity").alias("a"), F.col("l_extendedprice").alias("b"), days("l_shipdate").alias("t"), F.col("l_linenumber").cast("long").alias("w"))
    return geometry.as_points(t, PointSpec("uid", ("a", "b", "t"), "w"))


def lineitem10(spark: SparkSession, d: str) -> DataFrame:
    part = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_size", "p_retailprice")
    t = table(spark, d, "lineitem").join(part, "l_partkey")
    t = t.select(line_id().alias("uid"), "l_quantity", "l_extendedprice", (F.col("l_discount") + 0.0).alias("l_discount"), (F.col("l_tax") + 0.0).alias("l_tax"), days("l_shipdate").alias("t"), "l_partkey", "l_suppkey", "l_orderkey", "p_size", "p_retailprice")
    return geometry.as_points(t, PointSpec("uid", ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "t", "l_partkey", "l_suppkey", "l_orderkey", "p_size", "p_retailprice")))


def events(spark: SparkSession, d: str) -> DataFrame:
    return geometry.as_points(table(spark, d, "events"), PointSpec("event_id", ("ts", "value", "user_id")))


def unit(p: DataFrame, dims: int) -> DataFrame:
    """Scaled to the unit box of the set."""
    return geometry.unit_scale(p, dims, geometry.bounding_box(p, dims))


def cluster(spark: SparkSession, d: str) -> DataFrame:
    """Cubed unit coordinates of events (a cluster at the low corner), and orders with their customer as a third coordinate, uniform."""
    e = unit(events(spark, d), 3).select((F.col("uid") * 2).alias("uid"), *[(F.col(f"c{i}") * F.col(f"c{i}") * F.col(f"c{i}")).alias(f"c{i}") for i in range(3)], "w")
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice", days("o_orderdate").alias("t"), "o_custkey")
    o = unit(geometry.as_points(o, PointSpec("o_orderkey", ("o_totalprice", "t", "o_custkey"))), 3)
    return e.unionByName(o.select((F.col("uid") * 2 + 1).alias("uid"), "c0", "c1", "c2", "w"))


def cell_mesh(spark: SparkSession, d: str, bits: int) -> DataFrame:
    """uid, g0..g2: the grid cells that hold line items, once each; uid is the cell's number."""
    p = lineitem(spark, d)
    cells = geometry.quantise(p, 3, geometry.bounding_box(p, 3), bits)
    g = p.select(*[c.alias(f"g{i}") for i, c in enumerate(cells)]).distinct()
    return g.select(F.expr(f"(g0 * {1 << bits} + g1) * {1 << bits} + g2").alias("uid"), "g0", "g1", "g2")


# ---- SQL ----

_DAY = lambda c: f"date_diff('day', DATE '{DAY0}', CAST({c} AS DATE))"
LINE_ID = f"((CAST(round(l_extendedprice * 100) AS BIGINT) * 64 + CAST(l_quantity AS BIGINT)) * 4096 + {_DAY('l_shipdate')})"
ORDERS_SQL = f"SELECT o_orderkey AS uid, o_totalprice + 0.0::DOUBLE AS c0, CAST({_DAY('o_orderdate')} AS DOUBLE) AS c1, CAST(1 AS BIGINT) AS w FROM orders"
ORDERS_LINES_SQL = f"SELECT o_orderkey AS uid, o_totalprice + 0.0::DOUBLE AS c0, CAST({_DAY('o_orderdate')} AS DOUBLE) AS c1, CAST(coalesce(n, 0) AS BIGINT) AS w FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey"
LINES_SQL = f"SELECT {LINE_ID} AS uid, CAST(l_quantity AS DOUBLE) AS c0, CAST(l_extendedprice AS DOUBLE) AS c1, CAST({_DAY('l_shipdate')} AS DOUBLE) AS c2, CAST(1 AS BIGINT) AS w FROM lineitem"
LINES_W_SQL = LINES_SQL.replace("CAST(1 AS BIGINT) AS w", "CAST(l_linenumber AS BIGINT) AS w")
EVENTS_SQL = "SELECT event_id AS uid, CAST(epoch_us(ts) AS DOUBLE) AS c0, CAST(value AS DOUBLE) AS c1, CAST(user_id AS DOUBLE) AS c2, CAST(1 AS BIGINT) AS w FROM events"
_L10 = ("l_quantity", "l_extendedprice", "l_discount", "l_tax", _DAY("l_shipdate"), "l_partkey", "l_suppkey", "l_orderkey", "p_size", "p_retailprice")
LINES10_SQL = f"SELECT {LINE_ID} AS uid, " + ", ".join(f"CAST({c} AS DOUBLE) + 0.0 AS c{i}" for i, c in enumerate(_L10)) + ", CAST(1 AS BIGINT) AS w FROM lineitem JOIN part ON p_partkey = l_partkey"


def unit_sql(src: str, d: int) -> str:
    """Rows of a point query in the unit box: uid, c0.., w."""
    box = ", ".join(f"min(c{i}) AS lo{i}, max(c{i}) AS hi{i}" for i in range(d))
    cols = ", ".join(f"CASE WHEN hi{i} > lo{i} THEN (c{i} - lo{i}) / (hi{i} - lo{i}) ELSE 0.0 END AS c{i}" for i in range(d))
    return f"(SELECT uid, {cols}, w FROM ({src}) p, (SELECT {box} FROM ({src})) b)"


_ORDERS3 = f"SELECT o_orderkey AS uid, o_totalprice + 0.0::DOUBLE AS c0, CAST({_DAY('o_orderdate')} AS DOUBLE) AS c1, CAST(o_custkey AS DOUBLE) AS c2, CAST(1 AS BIGINT) AS w FROM orders"
CLUSTER_SQL = f"SELECT uid * 2 AS uid, c0 * c0 * c0 AS c0, c1 * c1 * c1 AS c1, c2 * c2 * c2 AS c2, w FROM {unit_sql(EVENTS_SQL, 3)} UNION ALL SELECT uid * 2 + 1 AS uid, c0, c1, c2, w FROM {unit_sql(_ORDERS3, 3)}"


def cells_sql(src: str, d: int, bits: int) -> str:
    """Adds q0..: grid cells."""
    q = ", ".join(f"LEAST(CAST(floor(c{i} * {float(1 << bits)}) AS BIGINT), {(1 << bits) - 1}) AS q{i}" for i in range(d))
    return f"(SELECT uid, w, {', '.join(f'c{i}' for i in range(d))}, {q} FROM {unit_sql(src, d)})"


def morton_expr(d: int, bits: int) -> str:
    return " | ".join(f"(((q{i} >> {k}) & 1) << {k * d + d - 1 - i})" for i in range(d) for k in range(bits))


def keyed_sql(src: str, d: int, bits: int) -> str:
    """uid, c0.. (unit box), w, key on the Morton curve."""
    return f"(SELECT uid, w, {', '.join(f'c{i}' for i in range(d))}, {morton_expr(d, bits)} AS key FROM {cells_sql(src, d, bits)})"


def hilbert3_sql(src: str, bits: int) -> str:
    """uid, key of cells (uid, q0..q2) on the three-dimensional Hilbert curve, from coordinates: rotations undone level by level, a Gray decoding, the
    carry of the last axis."""
    carry = "0::BIGINT"
    for k in range(1, bits):
        carry = f"xor({carry}, CASE WHEN (g2 >> {k}) & 1 = 1 THEN {(1 << k) - 1} ELSE 0 END)"
    key = " | ".join(f"(((xor(g{i}, t) >> {k}) & 1) << {k * 3 + 2 - i})" for i in range(3) for k in range(bits))
    return f"""(WITH RECURSIVE h(uid, a, b, c, q) AS (
      SELECT uid, CAST(q0 AS BIGINT), CAST(q1 AS BIGINT), CAST(q2 AS BIGINT), {1 << bits - 1}::BIGINT FROM {src}
      UNION ALL
      SELECT uid, CASE WHEN c & q > 0 THEN xor(a2, q - 1) ELSE xor(a2, xor(a2, c) & (q - 1)) END, b2, CASE WHEN c & q > 0 THEN c ELSE xor(c, xor(a2, c) & (q - 1)) END, q >> 1
      FROM (SELECT uid, q, c, CASE WHEN b & q > 0 THEN xor(a1, q - 1) ELSE xor(a1, xor(a1, b) & (q - 1)) END AS a2, CASE WHEN b & q > 0 THEN b ELSE xor(b, xor(a1, b) & (q - 1)) END AS b2
        FROM (SELECT uid, q, b, c, CASE WHEN a & q > 0 THEN xor(a, q - 1) ELSE a END AS a1 FROM h WHERE q > 1))
    ), g AS (SELECT uid, a AS g0, xor(a, b) AS g1, xor(xor(a, b), c) AS g2 FROM h WHERE q = 1),
    t AS (SELECT *, {carry} AS t FROM g) SELECT uid, {key} AS key FROM t)"""


def steps_sql(keyed: str) -> str:
    """steps, unit_share and mean_step over successive cells (q0..q2, key)."""
    return f"""SELECT count(*) AS steps, round(avg(CASE WHEN step = 1 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS unit_share, round(avg(step::DOUBLE), 6) AS mean_step FROM (
      SELECT abs(q0 - lag(q0) OVER w) + abs(q1 - lag(q1) OVER w) + abs(q2 - lag(q2) OVER w) AS step FROM {keyed} WINDOW w AS (ORDER BY key)) WHERE step IS NOT NULL"""


def mesh_sql(side: int) -> str:
    return f"(SELECT i AS uid, i // {side * side} AS q0, (i // {side}) % {side} AS q1, i % {side} AS q2 FROM range({side**3}) t(i))"


def cell_mesh_sql(bits: int) -> str:
    return f"(SELECT DISTINCT (q0 * {1 << bits} + q1) * {1 << bits} + q2 AS uid, q0, q1, q2 FROM {cells_sql(LINES_SQL, 3, bits)})"


def prefix_sql(src: str) -> str:
    """Adds prefix, total and rank in the order (key, uid)."""
    return f"(SELECT *, coalesce(CAST(sum(w) OVER (ORDER BY key, uid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS prefix, CAST(sum(w) OVER () AS BIGINT) AS total, row_number() OVER (ORDER BY key, uid) - 1 AS rank FROM {src})"


def part_expr(parts: int) -> str:
    return f"CAST(LEAST({parts - 1}, (prefix * {parts}) // total) AS INTEGER)"


HASH = "((((uid % 2147483647) * 2654435761) % 4294967296))"
