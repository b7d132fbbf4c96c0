"""One query for each surrounding operator that the methods need."""

from __future__ import annotations

from pyspark.sql import Window as W, functions as F

from curvebalance.functions import sqlfuncs
from curvebalance.operators import joins, kdtree
from curvebalance.sources.io import table
from curvebalance.streaming import windows

from . import points as P

QUERIES, ORACLE = {}, {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


T = table


@query("op_project", "SELECT o_orderkey AS k, CAST(o_totalprice AS BIGINT) AS p, upper(o_orderstatus) AS s FROM orders")
def _(s, d):
    return T(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.rint("o_totalprice").cast("long").alias("p"), F.upper("o_orderstatus").alias("s"))


@query("op_filter_box", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_extendedprice < 30000 AND l_returnflag IN ('A', 'N') AND l_shipdate IS NOT NULL")
def _(s, d):
    return T(s, d, "lineitem").where(F.col("l_quantity").between(10, 20) & (F.col("l_extendedprice") < 30000) & F.col("l_returnflag").isin("A", "N") & F.col("l_shipdate").isNotNull()).select("l_orderkey", "l_linenumber")


@query("op_join_inner", "SELECT o_custkey, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def _(s, d):
    return T(s, d, "orders").join(T(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n"))


@query("op_join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY 1")
def _(s, d):
    return T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("op_join_merge", "SELECT o_orderkey, count(l_linenumber) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def _(s, d):
    return T(s, d, "orders").hint("merge").join(T(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.count("l_linenumber").alias("n"))


@query("op_join_full", "SELECT a.uid AS a, b.uid AS b FROM (SELECT o_orderkey AS uid FROM orders WHERE o_orderkey % 3 <> 0) a FULL JOIN (SELECT o_orderkey AS uid FROM orders WHERE o_orderkey % 2 = 0) b ON a.uid = b.uid")
def _(s, d):
    o = T(s, d, "orders")
    a, b = o.where("o_orderkey % 3 <> 0").select(F.col("o_orderkey").alias("a")), o.where("o_orderkey % 2 = 0").select(F.col("o_orderkey").alias("b"))
    return a.join(b, F.col("a") == F.col("b"), "full")


@query("op_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def _(s, d):
    return T(s, d, "customer").join(T(s, d, "orders").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@query("op_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def _(s, d):
    return T(s, d, "customer").join(T(s, d, "orders").where("o_totalprice > 300000"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@query("op_theta", "SELECT a.s_suppkey AS a, b.n_nationkey AS b FROM supplier a JOIN nation b ON a.s_suppkey % 25 < b.n_nationkey")
def _(s, d):
    return T(s, d, "supplier").join(F.broadcast(T(s, d, "nation")), F.col("s_suppkey") % 25 < F.col("n_nationkey")).select(F.col("s_suppkey").alias("a"), F.col("n_nationkey").alias("b"))


@query("op_range_join", "SELECT o_orderkey, p_partkey FROM orders JOIN part ON o_orderkey BETWEEN p_partkey * 5 AND p_partkey * 5 + p_size")
def _(s, d):
    r = T(s, d, "part").select("p_partkey", (F.col("p_partkey") * 5).alias("lo"), (F.col("p_partkey") * 5 + F.col("p_size")).alias("hi"))
    return joins.range_join(T(s, d, "orders").select("o_orderkey"), "o_orderkey", r, "lo", "hi", 64).select("o_orderkey", "p_partkey")


@query("op_asof_join", "SELECT l.event_id, r.v FROM (SELECT event_id, user_id % 10 AS g, epoch_us(ts) AS t FROM events) l ASOF LEFT JOIN (SELECT user_id % 10 AS g, epoch_us(ts) AS t, max(event_id) AS v FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) r ON l.g = r.g AND l.t >= r.t")
def _(s, d):
    e = T(s, d, "events").select("event_id", (F.col("user_id") % 10).alias("g"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_type")
    r = e.where("event_type = 'purchase'").groupBy("g", "t").agg(F.max("event_id").alias("v"))
    return joins.asof_join(e.select("event_id", "g", "t"), r, "t", "v", "g").select("event_id", "v")


@query("op_self_join", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _(s, d):
    n = T(s, d, "nation").select("n_nationkey", "n_regionkey")
    return n.select(F.col("n_nationkey").alias("a"), "n_regionkey").join(n.select(F.col("n_nationkey").alias("b"), "n_regionkey"), "n_regionkey").where("a < b").select("a", "b")


@query("op_group_agg", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, round(avg(l_quantity), 6) AS a, round(stddev(l_quantity), 6) AS sd FROM lineitem GROUP BY 1, 2")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("q"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("a"), F.round(F.stddev("l_quantity"), 6).alias("sd"))


@query("op_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS n FROM lineitem GROUP BY 1")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("n"))


@query("op_approx_distinct")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_suppkey").alias("n"))


@query("op_percentile", "SELECT l_returnflag, quantile_disc(l_extendedprice, 0.5) AS m, quantile_disc(l_extendedprice, 0.9) AS p FROM lineitem GROUP BY 1")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY l_extendedprice)").alias("m"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY l_extendedprice)").alias("p"))


@query("op_kll_median")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D)").alias("m"))


_R = "SELECT n_regionkey, n_nationkey, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY "


def _cn(s, d):
    return T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey"))


@query("op_rollup", _R + "ROLLUP (n_regionkey, n_nationkey)")
def _(s, d):
    return _cn(s, d).rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


@query("op_cube", _R + "CUBE (n_regionkey, n_nationkey)")
def _(s, d):
    return _cn(s, d).cube("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


@query("op_grouping_sets", _R + "GROUPING SETS ((n_regionkey), (n_nationkey), ())")
def _(s, d):
    return _cn(s, d).groupingSets([["n_regionkey"], ["n_nationkey"], []], "n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))


@query("op_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS \"F\", count(*) FILTER (l_linestatus = 'O') AS \"O\" FROM lineitem GROUP BY 1")
def _(s, d):
    p = T(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count("l_orderkey"))
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).cast("long").alias("F"), F.coalesce("O", F.lit(0)).cast("long").alias("O"))


@query("op_max_by", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS k, count(*) FILTER (o_orderstatus = 'F') AS f FROM orders GROUP BY 1")
def _(s, d):
    return T(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("k"), F.expr("count(*) FILTER (WHERE o_orderstatus = 'F')").alias("f"))


@query("op_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER p AS r, dense_rank() OVER p AS dr, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey), p AS (PARTITION BY o_custkey ORDER BY o_orderstatus)")
def _(s, d):
    w, p = W.partitionBy("o_custkey").orderBy("o_orderkey"), W.partitionBy("o_custkey").orderBy("o_orderstatus")
    return T(s, d, "orders").select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("r"), F.dense_rank().over(p).cast("long").alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("op_lag", "SELECT o_orderkey, o_orderkey - lag(o_orderkey) OVER w AS step, lead(o_orderkey) OVER w AS nxt, first_value(o_orderkey) OVER w AS f FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def _(s, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderkey")
    return T(s, d, "orders").select("o_orderkey", (F.col("o_orderkey") - F.lag("o_orderkey").over(w)).alias("step"), F.lead("o_orderkey").over(w).alias("nxt"), F.first("o_orderkey").over(w).alias("f"))


@query("op_running_sum", "SELECT event_id, CAST(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return T(s, d, "events").select("event_id", F.sum("event_id").over(w).alias("s"))


@query("op_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS n FROM orders")
def _(s, d):
    return T(s, d, "orders").select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("o_orderkey").rangeBetween(-1000, 1000)).alias("n"))


@query("op_sort_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 10")
def _(s, d):
    return T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(50).select("o_orderkey", "o_totalprice")


@query("op_union", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def _(s, d):
    return T(s, d, "customer").select(F.col("c_nationkey").alias("k")).unionByName(T(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


@query("op_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def _(s, d):
    return T(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(T(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


@query("op_except", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def _(s, d):
    return T(s, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(T(s, d, "supplier").select(F.col("s_nationkey").alias("k")))


_NODES_BELOW = "WITH RECURSIVE t(p, k) AS (SELECT p, 0 FROM (SELECT DISTINCT o_custkey % 32 + 1 AS p FROM {}) r UNION ALL SELECT p * 2 + b, k + 1 FROM t, (VALUES (0), (1)) v(b) WHERE k < 5) SELECT p, k FROM t"


@query("op_recursive", _NODES_BELOW.format("orders"))
def _(s, d):
    """Nodes of five levels below those that customers of orders hash to."""
    T(s, d, "orders").createOrReplaceTempView("_recursive_orders")
    return s.sql(_NODES_BELOW.format("_recursive_orders"))


@query("op_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5::DOUBLE FROM orders) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)")
def _(s, d):
    o = T(s, d, "orders")
    cut = o.agg((F.avg("o_totalprice") * 1.5).alias("cut"))
    return o.crossJoin(F.broadcast(cut)).where("o_totalprice > cut").join(T(s, d, "customer").where("c_acctbal > 5000"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey")


@query("op_bits", "SELECT o_orderkey, o_orderkey << 3 AS a, o_orderkey >> 2 AS b, o_orderkey & 255 AS c, o_orderkey | 5 AS d, xor(o_orderkey, 12345) AS e, CAST(bit_count(o_orderkey) AS INTEGER) AS f FROM orders")
def _(s, d):
    k = F.col("o_orderkey")
    return T(s, d, "orders").select(k, F.shiftleft(k, 3).alias("a"), F.shiftright(k, 2).alias("b"), k.bitwiseAND(255).alias("c"), k.bitwiseOR(5).alias("d"), k.bitwiseXOR(12345).alias("e"), F.bit_count(k).alias("f"))


@query("op_math", "SELECT o_orderkey, round(sqrt(o_totalprice), 6) AS a, CAST(floor(o_totalprice / 7) AS BIGINT) AS b, greatest(o_orderkey, o_custkey) AS c, least(o_orderkey, o_custkey) AS d, o_orderkey % 11 AS e FROM orders")
def _(s, d):
    return T(s, d, "orders").select("o_orderkey", F.round(F.sqrt("o_totalprice"), 6).alias("a"), F.floor(F.col("o_totalprice") / 7).alias("b"), F.greatest("o_orderkey", "o_custkey").alias("c"), F.least("o_orderkey", "o_custkey").alias("d"), F.pmod("o_orderkey", F.lit(11)).alias("e"))


@query("op_width_bucket")
def _(s, d):
    return T(s, d, "orders").select("o_orderkey", F.expr("width_bucket(o_totalprice, 0, 500000, 16)").alias("b"), F.xxhash64("o_orderkey").alias("h"))


@query("op_string", "SELECT c_custkey, lower(c_name) AS a, substr(c_name, 1, 4) AS b, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS c, regexp_extract(c_name, '([0-9]+)', 1) AS d, trim('  ' || c_mktsegment || ' ') AS e FROM customer")
def _(s, d):
    return T(s, d, "customer").select("c_custkey", F.lower("c_name").alias("a"), F.substring("c_name", 1, 4).alias("b"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("c"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("d"), F.trim(F.concat(F.lit("  "), "c_mktsegment", F.lit(" "))).alias("e"))


@query("op_date", "SELECT o_orderkey, epoch_us(o_orderdate) AS a, CAST(extract('year' FROM o_orderdate) AS INTEGER) AS b, epoch_us(date_trunc('month', o_orderdate)::TIMESTAMP) AS c, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS d FROM orders")
def _(s, d):
    t = F.col("o_orderdate").cast("timestamp")
    return T(s, d, "orders").select("o_orderkey", F.unix_micros(t).alias("a"), F.year(t).alias("b"), F.unix_micros(F.date_trunc("month", t)).alias("c"), P.days("o_orderdate").alias("d"))


@query("op_array", "SELECT vec_id, len(embedding) AS n, round(CAST(embedding[1] AS DOUBLE), 6) AS a, round(list_max(embedding)::DOUBLE, 6) AS m FROM embeddings")
def _(s, d):
    e = F.col("embedding")
    return T(s, d, "embeddings").select("vec_id", F.size(e).cast("long").alias("n"), F.round(F.element_at(e, 1).cast("double"), 6).alias("a"), F.round(F.array_max(e).cast("double"), 6).alias("m"))


@query("op_explode", "SELECT o_orderkey, o_orderkey * 3 + i AS v FROM orders, range(0, 3) t(i)")
def _(s, d):
    return T(s, d, "orders").select("o_orderkey", F.explode(F.transform(F.sequence(F.lit(0), F.lit(2)), lambda i: F.col("o_orderkey") * 3 + i)).alias("v"))


@query("op_map", "SELECT n_regionkey, count(*) AS n, min(n_nationkey) AS lo FROM nation GROUP BY 1")
def _(s, d):
    m = T(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m"))
    return m.select("n_regionkey", F.cardinality("m").cast("long").alias("n"), F.array_min(F.map_values("m")).alias("lo"))


@query("op_json", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def _(s, d):
    return T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("op_null", "SELECT o_orderkey, CASE WHEN o_orderkey % 3 = 0 THEN NULL ELSE o_custkey END AS a, coalesce(nullif(o_orderkey % 5, 0), -1) AS b FROM orders")
def _(s, d):
    k = F.col("o_orderkey")
    return T(s, d, "orders").select("o_orderkey", F.when(k % 3 == 0, None).otherwise(F.col("o_custkey")).alias("a"), F.coalesce(F.nullif(k % 5, F.lit(0).cast("long")), F.lit(-1).cast("long")).alias("b"))


@query("op_hash_sample", f"SELECT uid FROM ({P.ORDERS_SQL}) WHERE {P.HASH} < {int(0.1 * (1 << 32))}")
def _(s, d):
    return P.orders(s, d).where(kdtree.in_sample(F.col("uid"), 0.1)).select("uid")


_W = "FROM (SELECT user_id % 8 AS cell, ts FROM events)"


def _load(s, d):
    return T(s, d, "events").withColumn("cell", F.col("user_id") % 8)


@query("op_tumbling", f"SELECT cell, (epoch_us(ts) // 21600000000) * 21600000000 AS start_us, count(*) AS n {_W} GROUP BY 1, 2")
def _(s, d):
    return windows.windowed_load(_load(s, d), "cell", "6 hours")


@query("op_sliding", f"SELECT cell, (epoch_us(ts) // 10800000000 - k) * 10800000000 AS start_us, count(*) AS n FROM (SELECT user_id % 8 AS cell, ts FROM events), range(0, 2) t(k) GROUP BY 1, 2")
def _(s, d):
    return windows.windowed_load(_load(s, d), "cell", "6 hours", "3 hours")


@query("op_session", "SELECT cell, min(t) AS start_us, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY cell ORDER BY t, event_id) AS sid FROM (SELECT user_id AS cell, event_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 43200000000 THEN 0 ELSE 1 END AS new FROM events)) GROUP BY cell, sid")
def _(s, d):
    return windows.session_load(T(s, d, "events").withColumn("cell", F.col("user_id")), "cell", "12 hours")


@query("op_sql_function", f"SELECT o_orderkey, {P.morton_expr(2, 16)} AS m, CAST(LEAST(15, (o_orderkey * 16) // 1000000) AS INTEGER) AS p FROM (SELECT o_orderkey, o_custkey % 65536 AS q0, o_orderkey % 65536 AS q1 FROM orders)")
def _(s, d):
    sqlfuncs.register(s)
    T(s, d, "orders").createOrReplaceTempView("_orders")
    return s.sql("SELECT o_orderkey, morton_key(o_custkey % 65536, o_orderkey % 65536) AS m, slice_of(o_orderkey, 1000000, 16) AS p FROM _orders")


@query("op_table_function", "SELECT CAST(3 AS BIGINT) AS x0, count(*) AS cells FROM (SELECT DISTINCT o_custkey % 256 AS x, o_orderkey % 256 AS y FROM orders) WHERE x BETWEEN 3 AND 102 AND y BETWEEN 5 AND 44")
def _(s, d):
    """A box as key ranges: they hold all cells of orders in the box. The ranges may hold others too, which the box itself rules out."""
    sqlfuncs.register(s)
    T(s, d, "orders").createOrReplaceTempView("_box_orders")
    return s.sql("SELECT 3L AS x0, CAST(count(*) AS BIGINT) AS cells FROM box_to_key_ranges(3, 5, 102, 44, 8) r JOIN (SELECT x, y, morton_key(x, y) AS k FROM (SELECT DISTINCT o_custkey % 256 AS x, o_orderkey % 256 AS y FROM _box_orders)) c ON c.k BETWEEN r.lo AND r.hi WHERE x BETWEEN 3 AND 102 AND y BETWEEN 5 AND 44")


@query("op_edges_roundtrip", "SELECT DISTINCT l_partkey AS row, l_suppkey AS col FROM lineitem")
def _(s, d):
    from curvebalance.plans.tables import shared_path
    from curvebalance.sources import io

    path = shared_path(s, "edges")
    io.write_edges(T(s, d, "lineitem").select(F.col("l_partkey").alias("row"), F.col("l_suppkey").alias("col")).distinct(), path)
    return io.read_edges(s, path)


@query("op_slices_roundtrip", "SELECT CAST(o_orderkey % 4 AS INTEGER) AS part, count(*) AS n FROM orders WHERE o_orderkey % 4 = 2 GROUP BY 1")
def _(s, d):
    """Slices as folders: the filter on part prunes all others."""
    from curvebalance.plans.tables import shared_path
    from curvebalance.sources import io

    path = shared_path(s, "slices")
    io.write_slices(T(s, d, "orders").select("o_orderkey", (F.col("o_orderkey") % 4).cast("int").alias("part")), path, "o_orderkey")
    return s.read.parquet(path).where("part = 2").groupBy("part").agg(F.count("*").alias("n"))
