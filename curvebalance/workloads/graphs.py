"""Graph and sparse-matrix partitions, and products with vectors."""

from __future__ import annotations

from pyspark.sql import functions as F

from curvebalance.operators import graph, metrics, slicing, spmv
from curvebalance.plans import tables
from curvebalance.sources.io import table

from . import points as P

QUERIES, ORACLE = {}, {}
PARTS = 16


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


def custpart(spark, d):
    """Customer by part, with the number of line items: a stashed matrix (row, col, val)."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("row"))
    j = table(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("col")).join(o, "l_orderkey")
    return tables.snapshot(j.groupBy("row", "col").agg(F.count("*").alias("val")), "custpart")


def partsupp(spark, d):
    return tables.snapshot(table(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("row"), F.col("l_suppkey").alias("col")).agg(F.count("*").alias("val")), "partsupp")


def bigrams(spark, d):
    return tables.snapshot(graph.bigram_graph(table(spark, d, "documents")), "bigrams")


CUSTPART = "SELECT o_custkey AS row, l_partkey AS col, count(*) AS val FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY 1, 2"
PARTSUPP = "SELECT l_partkey AS row, l_suppkey AS col, count(*) AS val FROM lineitem GROUP BY 1, 2"
BIGRAMS = """
SELECT a.id AS row, b.id AS col, count(*) AS val FROM (
  SELECT w[i] AS x, w[i + 1] AS y FROM (SELECT string_split(lower(text), ' ') AS w FROM documents WHERE text IS NOT NULL), LATERAL (SELECT unnest(range(1, len(w))) AS i))
JOIN words a ON a.word = x JOIN words b ON b.word = y GROUP BY 1, 2"""
WORDS = "words AS (SELECT word, row_number() OVER (ORDER BY encode(word)) - 1 AS id FROM (SELECT DISTINCT unnest(string_split(lower(text), ' ')) AS word FROM documents WHERE text IS NOT NULL))"
_M = "(SELECT row AS q0, col AS q1, row, col, val, CAST(1 AS BIGINT) AS w, (row << 31) | col AS uid FROM m)"


def bits_key(bits: int) -> str:
    return P.morton_expr(2, bits)


def sfc_sql(m: str, parts: int, bits: int = 20) -> str:
    """A wider grid only adds leading zero bits: the order, and so the slices, are the same."""
    return f"SELECT row, col, val, {P.part_expr(parts)} AS part FROM {P.prefix_sql('(SELECT *, ' + bits_key(bits) + ' AS key FROM ' + _M.replace('FROM m', 'FROM ' + m) + ')')}"


def row_sql(m: str, parts: int) -> str:
    return f"SELECT row, col, val, CAST((row * {parts}) // (SELECT max(row) + 1 FROM {m}) AS INTEGER) AS part FROM {m}"


def hash_sql(m: str, parts: int) -> str:
    return f"SELECT row, col, val, CAST(((((row * 2654435761) % 4294967296)) >> 8) % {parts} AS INTEGER) AS part FROM {m}"


def grid_sql(m: str, parts: int) -> str:
    s = round(parts**0.5)
    n = f"(SELECT greatest(max(row), max(col)) + 1 FROM {m})"
    return f"SELECT row, col, val, CAST((row * {s}) // {n} * {s} + (col * {s}) // {n} AS INTEGER) AS part FROM {m}"


def measures_sql(name: str, method: str, parts: int, assigned: str, m: str) -> str:
    """One row of measures of a partition; owners are equal chunks of the columns."""
    n = f"(SELECT max(col) + 1 FROM {m})"
    return f"""(WITH s AS ({assigned}), msg AS (SELECT owner AS src, part AS dst, count(*) AS n FROM (SELECT part, col, CAST((col * {parts}) // {n} AS INTEGER) AS owner FROM (SELECT DISTINCT part, col FROM s)) WHERE owner <> part GROUP BY 1, 2),
ends AS (SELECT src AS p, dst AS q FROM msg UNION SELECT dst, src FROM msg), loads AS (SELECT part, count(*) AS n FROM s GROUP BY 1)
SELECT '{name}' AS graph, '{method}' AS method, {parts} AS parts, (SELECT count(*) FROM s) // {parts} AS avg_load, (SELECT max(n) FROM loads) AS max_load,
 coalesce((SELECT max(c) FROM (SELECT count(DISTINCT q) AS c FROM ends GROUP BY p)), 0) AS max_degree, coalesce((SELECT max(n) FROM msg), 0) AS max_message,
 CAST(coalesce((SELECT max(v) FROM (SELECT sum(n) AS v FROM msg GROUP BY dst)), 0) AS BIGINT) AS max_volume, CAST(coalesce((SELECT sum(n) FROM msg), 0) AS BIGINT) AS total_volume)"""


def measured(name: str, method: str, parts: int, assigned, n_cols: int):
    """The same by DataFrame operations."""
    a = tables.snapshot(assigned, "assigned")
    load = a.groupBy("part").agg(F.count("*").alias("n")).agg((F.floor(F.sum("n") / parts)).cast("long").alias("avg_load"), F.max("n").alias("max_load"))
    msg = tables.snapshot(spmv.messages(a, n_cols, parts), "messages")
    m = load.crossJoin(metrics.degree_and_messages(msg, parts))  # one row each
    return m.select(F.lit(name).alias("graph"), F.lit(method).alias("method"), F.lit(parts).alias("parts"), "avg_load", "max_load", "max_degree", "max_message", "max_volume", "total_volume")


def shape(m):
    r = m.agg(F.max("row").alias("r"), F.max("col").alias("c")).first()
    return r["r"] + 1, r["c"] + 1


def partition(m, method: str, parts: int):
    rows, cols = shape(m)
    if method == "sfc":
        return graph.sfc_partition(m, parts)
    if method == "row":
        return graph.row_partition(m, parts, rows)
    if method == "grid":
        return graph.grid_partition(m, parts, max(rows, cols))
    return graph.hash_partition(m, parts)


SQL_OF = {"sfc": sfc_sql, "row": row_sql, "grid": grid_sql, "hash": hash_sql}


def comparison(name, make, methods, many):
    def run(spark, d):
        m = make(spark, d)
        _, cols = shape(m)
        out = None
        for p in many:
            for k in methods:
                r = measured(name, k, p, partition(m, k, p), cols)
                out = r if out is None else out.unionByName(r)
        return out

    return run


def comparison_sql(name, src, methods, many, more=""):
    return f"WITH {more}{', ' if more else ''}m AS MATERIALIZED ({src}) " + " UNION ALL ".join(f"SELECT * FROM {measures_sql(name, k, p, SQL_OF[k]('m', p), 'm')}" for p in many for k in methods)


for _name, _graph, _make, _src, _methods, _many, _more in (
    ("graph_rowwise_metrics", "custpart", custpart, CUSTPART, ("row",), (16, 64), ""),
    ("graph_sfc_metrics", "custpart", custpart, CUSTPART, ("sfc",), (16, 64), ""),
    ("graph_baselines", "custpart", custpart, CUSTPART, ("hash", "grid"), (16, 64), ""),
    ("graph_compare", "custpart", custpart, CUSTPART, ("row", "sfc"), (16, 32, 100), ""),
    ("graph_bigrams", "bigrams", bigrams, BIGRAMS, ("row", "sfc"), (64,), WORDS),
    ("graph_partsupp", "partsupp", partsupp, PARTSUPP, ("row", "sfc"), (16,), ""),
):
    query(_name, comparison_sql(_graph, _src, _methods, _many, _more))(comparison(_graph, _make, _methods, _many))


_S = f"m AS MATERIALIZED ({CUSTPART}), s AS MATERIALIZED ({sfc_sql('m', PARTS)})"
_N = "(SELECT max(col) + 1 FROM m)"
_DEP = f"SELECT part, col, CAST((col * {PARTS}) // {_N} AS INTEGER) AS chunk FROM (SELECT DISTINCT part, col FROM s)"


def _sliced(spark, d):
    m = custpart(spark, d)
    return tables.snapshot(graph.sfc_partition(m, PARTS), "sliced"), shape(m)[1]


@query("spmv_result", f"WITH m AS ({CUSTPART}) SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM m GROUP BY 1")
def _(spark, d):
    s, n = _sliced(spark, d)
    x = spark.range(n).select(F.col("id").alias("idx"), (1 + F.col("id") % 7).alias("x"))
    return spmv.multiply(s, x)


@query("spmv_intervals", f"WITH {_S}, d AS (SELECT DISTINCT part, col FROM s), g AS (SELECT *, col - row_number() OVER (PARTITION BY part ORDER BY col) AS run FROM d) SELECT part, min(col) AS lo, max(col) AS hi FROM g GROUP BY part, run")
def _(spark, d):
    return spmv.required_intervals(_sliced(spark, d)[0])


@query("spmv_intervals_owned", f"WITH {_S}, d AS (SELECT DISTINCT part, col FROM s), g AS (SELECT *, col - row_number() OVER (PARTITION BY part ORDER BY col) AS run FROM d), n AS (SELECT max(col) + 1 AS n FROM m) SELECT CAST(i AS INTEGER) AS part, 'x' AS side, (i * n + {PARTS} - 1) // {PARTS} AS lo, ((i + 1) * n + {PARTS} - 1) // {PARTS} - 1 AS hi, true AS owned FROM n, range({PARTS}) t(i) UNION ALL SELECT part, 'x', min(col), max(col), false FROM g GROUP BY part, run")
def _(spark, d):
    """Each part's own chunk of the vector next to the runs it needs."""
    s, n = _sliced(spark, d)
    return spmv.intervals_table(s, n, PARTS)


@query("spmv_dependents", f"WITH {_S} SELECT part, count(*) AS n FROM ({_DEP}) WHERE chunk <> part GROUP BY 1")
def _(spark, d):
    s, n = _sliced(spark, d)
    return spmv.dependents(s, n, PARTS).groupBy("part").agg(F.count("*").alias("n"))


_OWN = f"SELECT chunk, part AS owner FROM (SELECT chunk, part, row_number() OVER (PARTITION BY chunk ORDER BY count(*) DESC, part) AS rn FROM ({_DEP}) GROUP BY chunk, part) WHERE rn = 1"


@query("spmv_owners", f"WITH {_S} SELECT CAST(i AS INTEGER) AS chunk, coalesce(owner, CAST(i AS INTEGER)) AS owner FROM range({PARTS}) t(i) LEFT JOIN ({_OWN}) o ON o.chunk = i")
def _(spark, d):
    s, n = _sliced(spark, d)
    return spmv.reassign_owners(s, n, PARTS)


@query("spmv_volume", f"WITH {_S} SELECT 'equal chunks' AS method, count(*) AS total FROM ({_DEP}) WHERE chunk <> part UNION ALL SELECT 'overlap', count(*) FROM ({_DEP}) d JOIN ({_OWN}) o USING (chunk) WHERE o.owner <> d.part UNION ALL SELECT 'full replication', {_N} * {PARTS - 1}")
def _(spark, d):
    s, n = _sliced(spark, d)
    count = lambda df, name: df.agg(F.count("*").alias("total")).select(F.lit(name).alias("method"), "total")
    own = spmv.reassign_owners(s, n, PARTS)
    full = spark.range(1).select(F.lit("full replication").alias("method"), F.lit(metrics.full_replication_volume(n, PARTS)).cast("long").alias("total"))
    return count(spmv.dependents(s, n, PARTS), "equal chunks").unionByName(count(spmv.dependents(s, n, PARTS, owners=own), "overlap")).unionByName(full)


@query("spmv_owner_one_to_one")
def _(spark, d):
    s, n = _sliced(spark, d)
    return spmv.reassign_owners(s, n, PARTS, "one_to_one")


@query("spmv_spanning_set")
def _(spark, d):
    s, n = _sliced(spark, d)
    own, total = spmv.spanning_set(s, n, PARTS)
    return spark.createDataFrame([(c, p, float(total)) for c, p in sorted(own.items())], "chunk int, owner int, total double")


@query("spmv_comm_trees", f"WITH {_S} SELECT chunk AS owner, list_sort(list(DISTINCT part)) AS leaves, count(*) AS entries FROM ({_DEP}) WHERE chunk <> part GROUP BY 1")
def _(spark, d):
    s, n = _sliced(spark, d)
    return spmv.comm_trees(s, n, PARTS)


@query("spmv_scatter", f"WITH {_S}, y AS (SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM m GROUP BY 1) SELECT part, row AS idx, y FROM (SELECT part, row, CAST((row * {PARTS}) // (SELECT max(row) + 1 FROM m) AS INTEGER) AS o FROM (SELECT DISTINCT part, row FROM s)) JOIN y USING (row) WHERE o <> part")
def _(spark, d):
    m = custpart(spark, d)
    rows, n = shape(m)
    s = tables.snapshot(graph.sfc_partition(m, PARTS), "sliced")
    x = spark.range(n).select(F.col("id").alias("idx"), (1 + F.col("id") % 7).alias("x"))
    return spmv.scatter(spmv.multiply(s, x), s, rows, PARTS)


_POWER = f"WITH b AS (SELECT row, col, sum(val) AS val FROM (SELECT row, col, val FROM ({PARTSUPP}) UNION ALL SELECT col, row, val FROM ({PARTSUPP})) GROUP BY 1, 2), x0 AS (SELECT DISTINCT row AS idx, 1.0::DOUBLE AS x FROM b)"
for _k in range(3):
    _POWER += f", y{_k} AS (SELECT row, sum(val::DOUBLE * x) AS y FROM b JOIN x{_k} ON col = idx GROUP BY 1), x{_k + 1} AS (SELECT row AS idx, y / (SELECT max(abs(y)) FROM y{_k}) AS x FROM y{_k})"


@query("spmv_power", _POWER + " SELECT idx, round(x, 6) AS x FROM x3")
def _(spark, d):
    m = partsupp(spark, d)
    r, c = shape(m)
    both = m.unionByName(m.select(F.col("col").alias("row"), F.col("row").alias("col"), "val")).groupBy("row", "col").agg(F.sum("val").alias("val"))
    x = spark.range(max(r, c)).select(F.col("id").alias("idx"), F.lit(1.0).alias("x"))
    s = tables.snapshot(graph.sfc_partition(tables.snapshot(both, "square"), 8), "sliced")
    return spmv.power_iterate(s, x, 3).select("idx", F.round("x", 6).alias("x"))


@query("multi_matrix_load", " UNION ALL ".join(f"SELECT '{n}' AS matrix, part, count(*) AS n FROM (WITH m AS ({s}) {sfc_sql('m', PARTS)}) GROUP BY 2" for n, s in (("custpart", CUSTPART), ("partsupp", PARTSUPP))))
def _(spark, d):
    p = graph.partition_many({"custpart": custpart(spark, d), "partsupp": partsupp(spark, d)}, PARTS)
    return p.groupBy("matrix", "part").agg(F.count("*").alias("n"))


@query("graph_objective", f"WITH {_S}, msg AS (SELECT chunk AS src, part AS dst, count(*) AS n FROM ({_DEP}) WHERE chunk <> part GROUP BY 1, 2) SELECT (SELECT CAST(max(v) AS BIGINT) FROM (SELECT sum(n) AS v FROM msg GROUP BY src)) AS max_cut, (SELECT CAST(sum(n) AS BIGINT) FROM msg) AS total_cut, (SELECT max(c) FROM (SELECT count(*) AS c FROM msg GROUP BY dst)) AS max_in_degree, (SELECT max(c) FROM (SELECT count(*) AS c FROM msg GROUP BY src)) AS max_out_degree")
def _(spark, d):
    s, n = _sliced(spark, d)
    cuts = spmv.messages(s, n, PARTS).select(F.col("src").alias("src_part"), F.col("dst").alias("dst_part"), F.col("n").alias("w"))
    return metrics.objective(cuts).select("max_cut", "total_cut", "max_in_degree", "max_out_degree")


_CATEGORY = lambda c: f"(SELECT {c} AS v, row_number() OVER (ORDER BY {c}) AS k FROM (SELECT DISTINCT {c} FROM documents WHERE {c} IS NOT NULL))"
_VERTICES = f"SELECT doc_id AS uid, CAST(coalesce(n_chars, 0) AS DOUBLE) AS c0, CAST(coalesce(a.k, 0) AS DOUBLE) AS c1, CAST(coalesce(b.k, 0) AS DOUBLE) AS c2, CAST(1 AS BIGINT) AS w FROM documents LEFT JOIN {_CATEGORY('lang')} a ON a.v = lang LEFT JOIN {_CATEGORY('source')} b ON b.v = source"


@query("partition_vertices", f"SELECT CAST(p AS INTEGER) AS part, count(uid) AS n, CAST(coalesce(sum(w), 0) AS BIGINT) AS w FROM range({PARTS}) t(p) LEFT JOIN (SELECT uid, w, {P.part_expr(PARTS)} AS part FROM {P.prefix_sql(P.keyed_sql(_VERTICES, 3, 16))}) s ON s.part = p GROUP BY p")
def _(spark, d):
    from curvebalance.functions.geometry import AttrSpec

    v = table(spark, d, "documents")
    p = graph.partition_vertices(v, "doc_id", [AttrSpec("n_chars"), AttrSpec("lang", "category"), AttrSpec("source", "category")], PARTS)
    return slicing.loads(p.withColumn("w", F.lit(1).cast("long")), PARTS)
