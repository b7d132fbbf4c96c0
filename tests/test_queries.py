"""Every query with SQL gives DuckDB's rows at the smallest scale; a sample of them, to keep the suite short (the driver runs all)."""

import pytest

import oracle
from curvebalance.workloads import ORACLE_SQL, QUERIES

SOME = ["morton_lineitem", "gray_orders", "hilbert_orders_2d", "slice_loads", "full_balance_lineitem", "transfer_rounds", "incremental_moves", "kd_midpoint_lineitem", "kd_levels_median", "dyn_insert_delete", "dyn_adjust", "amortised_trace", "locate_key", "knn_recall", "box_query", "graph_baselines", "spmv_volume", "multi_matrix_load", "op_asof_join", "op_range_join", "op_session", "op_sql_function"]


@pytest.fixture(scope="module")
def con(sf):
    return oracle.connect(sf)


@pytest.mark.parametrize("name", SOME)
def test_same_rows(spark, sf, con, name):
    assert oracle.compare(QUERIES[name](spark, sf), ORACLE_SQL[name], con) is None


def test_every_sql_has_a_query():
    assert set(ORACLE_SQL) <= set(QUERIES)


@pytest.fixture(scope="module")
def copies(sf, tmp_path_factory):
    """The tables with three copies of line items, two of every fourth: their keys differ, their ids of points do not."""
    import duckdb

    to = tmp_path_factory.mktemp("copies")
    shifted = "SELECT * REPLACE (l_orderkey + i * 100000 AS l_orderkey, 1 + (l_partkey + i * 7) % 200 AS l_partkey) FROM"
    duckdb.execute(f"COPY ({shifted} '{sf}/lineitem.parquet', range(3) t(i) WHERE i < 2 OR l_orderkey % 4 > 0) TO '{to}/lineitem.parquet'")
    duckdb.execute(f"COPY (SELECT * FROM '{sf}/part.parquet') TO '{to}/part.parquet'")
    return str(to)


EQUAL_IDS = ["kd_midpoint_lineitem", "kd_median_lineitem", "kd_10d", "kd_nodes", "kd_leaf_order", "dyn_adjust", "dyn_adjust_tasks", "dyn_insert_delete", "dyn_points_10d", "dyn_table_3d"]


@pytest.mark.parametrize("name", EQUAL_IDS)
def test_same_rows_where_points_share_an_id(spark, copies, name):
    assert oracle.compare(QUERIES[name](spark, copies), ORACLE_SQL[name], oracle.connect(copies)) is None


FROM_TABLES = ["amr_stencil", "curve_steps", "hilbert_mesh", "op_recursive", "op_table_function", "surface_to_volume"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_reads_a_given_table(spark, sf, con, name):
    found = QUERIES[name](spark, sf)
    assert "parquet" in found._jdf.queryExecution().executedPlan().toString().lower()
    assert any(t in ORACLE_SQL[name] for t in ("lineitem", "orders"))
    assert oracle.compare(found, ORACLE_SQL[name], con) is None
