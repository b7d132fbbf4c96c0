"""Hand-checked examples, invariants and edge cases of the curve engine."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import oracle
from curvebalance.functions import curves, geometry
from curvebalance.operators import amortise, amr, balance, dynamic, graph, kdtree, knn, locate, metrics, migrate, ranges, slicing, spmv
from curvebalance.plans.specs import PointSpec, TreeConfig
from curvebalance.sources import datagen
from curvebalance.workloads import ORACLE_SQL, QUERIES


def points(spark, rows, dims=1):
    return spark.createDataFrame([tuple(r) for r in rows], "uid long, " + ", ".join(f"c{i} double" for i in range(dims)) + ", w long")


def line(spark, weights):
    return spark.createDataFrame([(i, i, w) for i, w in enumerate(weights)], "uid long, key long, w long")


def parts(df):
    return [r["part"] for r in df.orderBy("uid").collect()]


def test_slices_by_prefix(spark):
    assert parts(slicing.slice_curve(line(spark, range(1, 9)), 3)) == [0, 0, 0, 0, 0, 1, 1, 2]
    assert [r["w"] for r in slicing.loads(slicing.slice_curve(line(spark, range(1, 9)), 3), 3).orderBy("part").collect()] == [15, 13, 8]


def test_unit_weights_differ_by_one(spark):
    assert [r["n"] for r in slicing.loads(slicing.slice_curve(line(spark, [1] * 10), 4), 4).orderBy("part").collect()] == [3, 2, 3, 2]


@pytest.mark.parametrize("seed", [1, 2])
def test_refined_slices_stay_within_the_heaviest_point(spark, seed):
    w = np.random.default_rng(seed).integers(1, 30, 80).tolist()
    s = slicing.slice_curve(line(spark, w), 7, "refined")
    load = [r["w"] for r in slicing.loads(s, 7).collect()]
    assert max(load) - min(load) <= max(w) and sum(load) == sum(w)
    assert parts(s) == sorted(parts(s))


def test_fewer_points_than_parts_and_zero_weights(spark):
    s = slicing.slice_curve(line(spark, [1, 1]), 8)
    assert sum(r["n"] for r in slicing.loads(s, 8).collect()) == 2
    assert parts(slicing.slice_curve(line(spark, [0, 0, 0]), 2)) == [0, 0, 0]
    assert slicing.slice_curve(line(spark, [1]).where("uid < 0"), 4).count() == 0


def test_prefix_over_many_ranges_equals_one_window(spark):
    w = np.random.default_rng(3).integers(1, 9, 500)
    df = spark.createDataFrame([(i, int(i * 7919 % 503) // 3, int(x)) for i, x in enumerate(w)], "uid long, key long, w long")
    got = slicing.slice_curve(df, 5, n=17).orderBy("key", "uid").collect()
    assert [r["prefix"] for r in got] == np.concatenate(([0], np.cumsum([r["w"] for r in got])[:-1])).tolist()


def test_morton_values(spark):
    df = spark.createDataFrame([(2, 3), (0, 0), (3, 3), (1, 2)], "x long, y long")
    assert [r[0] for r in df.select(curves.interleave([F.col("x"), F.col("y")], 2)).collect()] == [13, 0, 15, 6]


@pytest.mark.parametrize("dims,bits", [(2, 2), (2, 3), (3, 3), (4, 2)])
def test_hilbert_steps_are_unit_steps(spark, dims, bits):
    side = 1 << bits
    g = datagen.mesh(spark, side, dims)
    cells = [F.col(f"g{i}") for i in range(dims)]
    rows = g.withColumn("key", curves.hilbert_key(cells, bits)).orderBy("key").collect()
    at = np.array([[r[f"g{i}"] for i in range(dims)] for r in rows])
    assert [r["key"] for r in rows] == list(range(side**dims))
    assert (np.abs(np.diff(at, axis=0)).sum(1) == 1).all()
    if dims == 2:
        two = g.withColumn("key", curves.hilbert_key_2d(*cells, bits)).orderBy("key").collect()
        at = np.array([[r["g0"], r["g1"]] for r in two])
        assert (np.abs(np.diff(at, axis=0)).sum(1) == 1).all()


@pytest.mark.parametrize("dims", [2, 3])
def test_tree_hilbert_on_a_full_grid(dims):
    side = 8
    g = np.stack(np.meshgrid(*[np.arange(side)] * dims, indexing="ij"), -1).reshape(-1, dims) / (side - 1)
    uid = np.arange(len(g))
    b = kdtree.build_subtree(uid, g, TreeConfig.of("midpoint", bucket_size=1), want_nodes=True)
    order = [p for p, _, _ in kdtree.hilbert_walk({p: d for p, _, d, _, leaf, *_ in b.nodes if not leaf}, dims)]
    at = {int(p): g[i] * (side - 1) for i, p in enumerate(b.path)}
    steps = np.abs(np.diff(np.array([at[p] for p in order]), axis=0)).sum(1)
    assert len(order) == side**dims and np.allclose(steps, 1)


def test_wide_key_sorts_like_the_number(spark):
    df = spark.createDataFrame([(i * 37 % 64, i * 11 % 64) for i in range(64)], "x long, y long")
    k = df.select(curves.interleave([F.col("x"), F.col("y")], 6).alias("k"), curves.wide_key([F.col("x"), F.col("y")], 6).alias("b"))
    assert [r["k"] for r in k.orderBy("b", "k").collect()] == sorted(r["k"] for r in k.collect())


def test_tree_of_ten_values():
    c = np.arange(1.0, 11)[:, None]
    for s in ("midpoint", "median_sort"):
        b = kdtree.build_subtree(np.arange(10), (c - 1) / 9, TreeConfig.of(s, bucket_size=3), want_nodes=True)
        leaves = {}
        for v, p in zip(c[:, 0], b.path):
            leaves.setdefault(int(p), []).append(int(v))
        assert sorted(leaves.values()) == [[1, 2, 3], [4, 5], [6, 7, 8], [9, 10]] and len(b.nodes) == 7


def test_ties_make_an_oversize_leaf():
    b = kdtree.build_subtree(np.arange(6), np.array([[1.0]] * 5 + [[9.0]]), TreeConfig.of("median_sort", bucket_size=2), want_nodes=True)
    assert len(b.nodes) == 3 and sorted(np.unique(b.path, return_counts=True)[1]) == [1, 5]


@pytest.mark.parametrize("splitter", ["midpoint", "median_sort"])
def test_distributed_tree_equals_local_and_level_builds(spark, splitter):
    p = datagen.clustered(spark, 900, 2)
    u = geometry.unit_scale(p, 2, geometry.bounding_box(p, 2)).cache()
    rows = u.orderBy("uid").collect()
    want = kdtree.build_subtree(np.array([r["uid"] for r in rows]), np.array([[r["c0"], r["c1"]] for r in rows]), TreeConfig.of(splitter, bucket_size=16)).path.tolist()
    cfg = TreeConfig.of(splitter, bucket_size=16, k1=8)
    assert [r["path"] for r in kdtree.build(u, 2, cfg).members.orderBy("uid").collect()] == want
    assert [r["path"] for r in kdtree.build_levels(u, 2, cfg).orderBy("uid").collect()] == want


def test_medians_stay_shallow_where_midpoints_go_deep():
    r = np.random.default_rng(0)
    c = r.exponential(size=(4000, 2)) ** 5
    c = (c - c.min(0)) / (c.max(0) - c.min(0))
    depth = {s: kdtree.build_subtree(np.arange(4000), c, TreeConfig.of(s)).depth.max() for s in ("midpoint", "median_sort")}
    assert depth["median_sort"] < depth["midpoint"]


def test_sampled_median_error_shrinks():
    r = np.random.default_rng(1)
    x, uid = r.random(20000), r.permutation(20000)
    err = [abs((x <= kdtree.split_value(x, uid, "median_sample_select", f)).mean() - 0.5) for f in (0.001, 0.3)]
    assert err[1] < err[0] and kdtree.split_value(x, uid, "median_sample_select", 0.3) == kdtree.split_value(x, uid, "median_sample_sort", 0.3)


def test_merges_after_deletions():
    # root(A(9 points, empty), C(1, 2)) with B = 4: the nine are for the split step, C becomes a leaf of three
    to = dynamic.adjust_nodes({4: (2, 9), 5: (2, 0), 6: (2, 1), 7: (2, 2)}, 4)
    assert to == {4: 4, 6: 3, 7: 3}
    assert dynamic.adjust_nodes({4: (2, 1), 6: (2, 1), 7: (2, 2)}, 4) == {4: 1, 6: 1, 7: 1}


def test_merge_table_equals_node_rules(spark):
    r = np.random.default_rng(5)
    leaves = {}
    for p in range(32, 64):
        leaves[p] = (5, int(r.integers(0, 6)))
    to = dynamic.adjust_nodes(leaves, 6)
    want = {}
    for p, q in to.items():
        want[q] = want.get(q, 0) + leaves[p][1]
    df = spark.createDataFrame([(p, d, n) for p, (d, n) in leaves.items()], "path long, depth int, n long")
    assert {x["path"]: x["n"] for x in dynamic.merge_light(df, 6).collect()} == want


def test_heavy_means_more_than_twice(spark):
    cfg = TreeConfig.of("midpoint", bucket_size=4)
    def members(n):
        return spark.createDataFrame([(i, i / n, 1, 1, 1, 0) for i in range(n)], "uid long, c0 double, w long, top_id long, path long, depth int")
    assert dynamic.adjust(members(8), 1, cfg).select("path").distinct().count() == 1
    sizes = [r["count"] for r in dynamic.adjust(members(9), 1, cfg).groupBy("path").count().collect()]
    assert max(sizes) <= 4 and sum(sizes) == 9


def test_operations_last_wins_absent_are_handled(spark):
    p = points(spark, [(1, 0.1, 1), (2, 0.2, 1)])
    ops = spark.createDataFrame([("delete", 1, 1, 1, 0.0, 1), ("insert", 2, 2, 1, 0.9, 1), ("delete", 1, 3, 7, 0.0, 1), ("update", 1, 4, 8, 0.8, 1)], "op string, op_ts int, op_id int, uid long, c0 double, w long")
    assert sorted((r["uid"], r["c0"]) for r in dynamic.apply_ops(p, ops).collect()) == [(1, 0.9), (2, 0.2), (8, 0.8)]


def test_controller_spends_credit():
    c = amortise.Controller(balance_cost=10, buckets=5)
    debts, when = [], []
    for t in (2, 2.4, 1, 3, 2.8, 4):
        if c.observe(t):
            when.append(len(c.trace))
            debts.append(c.trace[-1]["debt"])
            c.rebalanced(10)
        else:
            debts.append(c.trace[-1]["debt"])
    assert np.allclose(debts, [0, 2, 2, 7, 11, 0]) and when == [5] and c.trace[-1]["base"] == 20


def test_migration_rounds_and_shares(spark):
    t = spark.createDataFrame([(0, 1, 10)], "src int, dst int, n long")
    assert [r["n"] for r in migrate.rounds(t, 4, 1).orderBy("round").collect()] == [4, 4, 2]
    before = balance.Balance(slicing.slice_curve(line(spark, [1] * 8), 2), 2, "full").assigned
    w = spark.createDataFrame([(i, 3 if i < 2 else 1) for i in range(8)], "uid long, w long")
    after = balance.incremental(before, w, 2).assigned
    assert parts(after) == [0, 0, 1, 1, 1, 1, 1, 1]
    m = balance.moved(before, after)
    assert {r["step_size"]: r["n"] for r in m.collect()} == {0: 6, 1: 2} and migrate.neighbour_share(m) == 1.0
    same = balance.incremental(before, None, 2).assigned
    assert parts(same) == parts(before)


COO = [(0, 0), (0, 3), (1, 1), (1, 2), (2, 0), (2, 2), (3, 1), (3, 3)]


def test_small_matrix_measures(spark):
    m = spark.createDataFrame([(r, c, 1) for r, c in COO], "row long, col long, val long")
    for p in (graph.row_partition(m, 2, 4), graph.sfc_partition(m, 2)):
        x = metrics.degree_and_messages(spmv.messages(p, 4, 2), 2).first()
        assert (x["max_degree"], x["max_message"], x["total_volume"]) == (1, 2, 4)
    four = graph.sfc_partition(m, 4)
    x = metrics.degree_and_messages(spmv.messages(four, 4, 4), 4).first()
    assert (x["max_degree"], x["max_message"], x["total_volume"]) == (3, 1, 6)
    own = spmv.reassign_owners(four, 4, 4)
    assert [r["owner"] for r in own.orderBy("chunk").collect()] == [0, 0, 1, 1]
    x = metrics.degree_and_messages(spmv.messages(four, 4, 4, owners=own), 4).first()
    assert (x["max_degree"], x["max_message"], x["total_volume"]) == (1, 2, 4)


def test_product_is_the_same_for_every_partition(spark):
    m = spark.createDataFrame([(r, c, r + 2 * c + 1) for r, c in COO], "row long, col long, val long")
    x = spark.createDataFrame([(i, i + 1) for i in range(4)], "idx long, x long")
    a = np.zeros((4, 4), int)
    for r, c in COO:
        a[r, c] = r + 2 * c + 1
    for p in (graph.row_partition(m, 2, 4), graph.sfc_partition(m, 4), graph.hash_partition(m, 3), graph.grid_partition(m, 4, 4)):
        assert [r["y"] for r in spmv.multiply(p, x).orderBy("row").collect()] == (a @ np.arange(1, 5)).tolist()


def test_intervals_and_gaps(spark):
    m = spark.createDataFrame([(0, c, 1, 0) for c in (0, 1, 2, 5, 6, 9)], "row long, col long, val long, part int")
    assert sorted((r["lo"], r["hi"]) for r in spmv.required_intervals(m).collect()) == [(0, 2), (5, 6), (9, 9)]
    assert sorted((r["lo"], r["hi"]) for r in spmv.required_intervals(m, max_gap=2).collect()) == [(0, 9)]


def test_curve_slices_need_fewer_peers_than_rows(spark):
    r = np.random.default_rng(2)
    rows = {(int(a), int(b)) for a, b in r.integers(0, 256, (6000, 2))}
    m = spark.createDataFrame([(a, b, 1) for a, b in sorted(rows)], "row long, col long, val long").cache()
    got = {}
    for k, p in (("row", graph.row_partition(m, 16, 256)), ("sfc", graph.sfc_partition(m, 16))):
        got[k] = metrics.degree_and_messages(spmv.messages(p, 256, 16), 16).first()
        if k == "sfc":
            assert max(x["count"] for x in p.groupBy("part").count().collect()) == -(-len(rows) // 16)
    assert got["row"]["max_degree"] == 15 and got["sfc"]["max_degree"] < 15 and got["sfc"]["total_volume"] < got["row"]["total_volume"]


def test_location_by_all_methods(spark):
    p = datagen.uniform(spark, 600, 2).cache()
    q = p.where("uid % 7 = 0").select(F.col("uid").alias("qid"), "c0", "c1").unionByName(spark.createDataFrame([(-1, 0.5, 0.123), (-2, 7.0, 7.0)], "qid long, c0 double, c1 double"))
    want = sorted((r["qid"], r["uid"]) for r in locate.by_join(p, q, 2).na.fill(-9, ["uid"]).collect())
    assert sorted((r["qid"], r["uid"]) for r in locate.by_key(p, q, 2, bucket_size=8).na.fill(-9, ["uid"]).collect()) == want
    tree = kdtree.build(p, 2, TreeConfig.of("median_sort", bucket_size=8, k1=8))
    assert sorted((r["qid"], r["uid"]) for r in locate.by_tree(tree, q).na.fill(-9, ["uid"]).collect()) == want
    with pytest.raises(ValueError):
        locate.auto(tree, p, q, "key")


def test_asof_window_search_equals_the_array_search(spark, monkeypatch):
    p = datagen.uniform(spark, 400, 2).cache()
    q = p.where("uid % 5 = 0").select(F.col("uid").alias("qid"), "c0", "c1")
    monkeypatch.setattr(locate, "SEARCHED", 0)
    assert locate.by_key(p, q, 2, bucket_size=8).where("found and qid = uid").count() == q.count()


def test_recall_rises_to_one(spark):
    p = datagen.uniform(spark, 800, 2)
    k = knn.buckets(curves.keyed(p, 2, 10, box=[(0.0, 1.0)] * 2), 16).cache()
    q = k.where("uid % 10 = 0").withColumnRenamed("uid", "qid").select("qid", "c0", "c1", "bucket")
    e = knn.exact(k, q, 2, 3).cache()
    r = [metrics.knn_recall(knn.by_curve(k, q, 2, 3, c), e, 3).first()["recall"] for c in (0, 2, 60)]
    assert r[0] < r[1] <= r[2] == 1.0 and r[1] > 0.8


def test_exact_search_answers_more_queries_than_a_block(spark, monkeypatch):
    monkeypatch.setattr(knn, "EXACT_QUERIES", 7)
    r = np.random.default_rng(3)
    xy, ask = r.random((300, 2)), r.random((40, 2))
    p = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "uid long, c0 double, c1 double")
    q = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(ask)], "qid long, c0 double, c1 double")
    got = {(x["qid"], x["rn"]): x["uid"] for x in knn.exact(p, q, 2, 3).collect()}
    d2 = ((ask[:, None] - xy[None]) ** 2).sum(2)
    assert got == {(i, n + 1): int(u) for i in range(40) for n, u in enumerate(np.argsort(d2[i])[:3])}
    assert knn.exact(p, q.limit(0), 2, 3).count() == 0


def test_exact_queries_leave_none_out(spark, sf, monkeypatch):
    monkeypatch.setattr(knn, "EXACT_QUERIES", 40)
    con = oracle.connect(sf)
    for name in ("knn_exact", "knn_recall"):
        assert oracle.compare(QUERIES[name](spark, sf), ORACLE_SQL[name], con) is None


@pytest.mark.parametrize("exclude_self", [False, True])
def test_search_prunes_and_equals_brute_force(monkeypatch, exclude_self):
    r = np.random.default_rng(5)
    c = np.round(r.random((6000, 3)) ** 2, 2)  # many equal distances
    uid, ask = np.arange(6000), np.arange(0, 6000, 60)
    by, starts = np.argsort(knn._codes(c), kind="stable"), np.arange(0, 6000, 32)
    measured, squares = [], knn._sum_squares
    monkeypatch.setattr(knn, "_sum_squares", lambda x: measured.append(len(x)) or squares(x))
    need = 4 if exclude_self else 3
    qi, at, d2 = knn._nearest(uid[by], c[by], starts, knn._box_levels(c[by], starts), ask, c[ask], np.full(100, np.inf), 3, need, exclude_self)
    assert sum(measured) < 6000 * 100 / 5
    for i, q in enumerate(ask):
        far = squares(c[q] - c)
        order = [u for u in np.lexsort((uid, far)) if not (exclude_self and u == q)][:3]
        assert uid[by][at[qi == i]].tolist() == order and d2[qi == i].tolist() == far[order].tolist()


def test_subtree_search_of_copies_meets_cells_not_pairs(spark):
    p = datagen.uniform(spark, 900, 2)
    p = p.unionByName(p.where("uid % 3 = 0")).cache()  # equal rows
    tree = kdtree.build(p, 2, TreeConfig.of("midpoint", bucket_size=8, k1=8))
    found = knn.by_subtree(tree, p.where("uid % 45 = 0").withColumnRenamed("uid", "qid"), 5, 0.08)
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "CoGroup" in plan  # points and queries meet in the cell's task; no table of pairs is made
    rows = [(x["uid"], x["c0"], x["c1"]) for x in p.collect()]
    got = [(x["qid"], x["rn"], x["uid"]) for x in found.orderBy("qid", "rn").collect()]
    want = []
    for q, x, y in {r for r in rows if r[0] % 45 == 0}:
        near = sorted(((x - a) * (x - a) + (y - b) * (y - b), u) for u, a, b in rows for _ in range(2 - bool(q % 3)))
        want += [(q, i + 1, u) for i, (d, u) in enumerate([n for n in near if n[0] <= 0.08 * 0.08][:5])]
    assert got == sorted(want)


def test_exact_search_takes_one_pass_and_counts_copies(spark, monkeypatch):
    monkeypatch.setattr(knn, "CHUNK", 100)
    p = datagen.uniform(spark, 600, 3)
    p = p.unionByName(p.where("uid % 2 = 0")).cache()
    q = p.where("uid % 20 = 4").withColumnRenamed("uid", "qid").unionByName(p.where("uid = 7").select((-F.col("uid")).alias("qid"), (F.col("c0") - 3).alias("c0"), "c1", (F.col("c2") + 2).alias("c2"), "w"))
    monkeypatch.setattr(knn, "EXACT_QUERIES", 3)
    found = knn.exact(p, q, 3, 6)
    assert "CoGroup" in found._jdf.queryExecution().optimizedPlan().toString()  # not a pass of all points for each block of queries
    got = [(x["qid"], x["rn"], x["uid"], x["d2"]) for x in found.orderBy("qid", "rn").collect()]
    d2 = "(q.c0 - p.c0) * (q.c0 - p.c0) + (q.c1 - p.c1) * (q.c1 - p.c1) + (q.c2 - p.c2) * (q.c2 - p.c2)"
    p.createOrReplaceTempView("_knn_p"), q.createOrReplaceTempView("_knn_q")
    want = spark.sql(f"SELECT qid, rn, uid, round(d2, 12) FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, uid) AS rn FROM (SELECT qid, uid, {d2} AS d2 FROM _knn_q q CROSS JOIN _knn_p p)) WHERE rn <= 6 ORDER BY qid, rn").collect()
    assert got == [tuple(x) for x in want]


def test_cutoffs_by_one_join_equal_each_alone(spark):
    k = knn.buckets(curves.keyed(datagen.uniform(spark, 500, 2), 2, 10, box=[(0.0, 1.0)] * 2), 16).cache()
    q = k.where("uid % 25 = 0").withColumnRenamed("uid", "qid").select("qid", "c0", "c1", "bucket")
    q = q.unionByName(q.where("qid % 2 = 0").withColumn("bucket", F.col("bucket") + 1)).cache()  # one id in two buckets
    rows = lambda df: sorted(map(tuple, df.select("qid", "rn", "uid", "d2").collect()))
    every = knn.by_curves(k, q, 2, 4, (0, 1, 3)).cache()
    for c in (0, 1, 3):
        j = q.alias("q").join(k.alias("p"), F.abs(F.col("q.bucket") - F.col("p.bucket")) <= c)
        d2 = sum(((F.col(f"q.c{i}") - F.col(f"p.c{i}")) * (F.col(f"q.c{i}") - F.col(f"p.c{i}")) for i in (1,)), (F.col("q.c0") - F.col("p.c0")) * (F.col("q.c0") - F.col("p.c0")))
        want = knn._rank(j.select("qid", "uid", d2.alias("d2")), 4)
        assert rows(every.where(F.col("cutoff") == c)) == rows(want) == rows(knn.by_curve(k, q, 2, 4, c))


def test_traces_have_all_stated_steps(spark, sf, monkeypatch):
    t = QUERIES["dyn_trace"](spark, sf).collect()
    assert len(t) == 10 and sum(x["adjusted"] for x in t) == 2 and all(x["n_ops"] for x in t)
    steps = []
    monkeypatch.setattr(amr, "run", lambda p, dims, parts, n, *rest, **kw: steps.append(n) or [{"rebalanced": False, "cost": 1.0}])
    QUERIES["amr_policy_compare"](spark, sf)
    assert steps == [20, 20, 20]


def test_key_ranges_cover_a_box_exactly():
    spans = ranges.key_ranges([3, 5], [12, 9], 4, most=1000)
    def morton(x, y):
        return sum((x >> k & 1) << 2 * k + 1 | (y >> k & 1) << 2 * k for k in range(4))
    inside = {morton(x, y) for x in range(3, 13) for y in range(5, 10)}
    assert {k for a, b in spans for k in range(a, b + 1)} == inside


def test_bad_points_are_refused(spark):
    df = spark.createDataFrame([(1, 0.5), (1, float("nan"))], "id long, x double")
    with pytest.raises(Exception):
        geometry.as_points(df, PointSpec("id", ("x",))).collect()
    with pytest.raises(ValueError):
        geometry.as_points(df.where("id = 1 and not isnan(x)").unionByName(df.where("not isnan(x)")), PointSpec("id", ("x",)), True)
    with pytest.raises(ValueError):
        PointSpec("id", ("y",)).check(df)
    with pytest.raises(ValueError):
        PointSpec("id", ("x",)).check(df.withColumn("x", F.lit("a")))


def test_identical_points_and_one_point(spark):
    p = points(spark, [(i, 0.5, 0.5, 1) for i in range(40)], 2)
    box = geometry.bounding_box(p, 2)
    t = kdtree.build(geometry.unit_scale(p, 2, box), 2, TreeConfig.of("midpoint", bucket_size=4))
    assert [r["path"] for r in t.members.select("path").distinct().collect()] == [1]
    assert geometry.bounding_box(p.where("uid < 0"), 2) is None
    assert curves.keyed(p.where("uid = 0"), 2).first()["key"] == 0


def test_plans_stay_distributed_and_pruned(spark, sf):
    from curvebalance.workloads import QUERIES

    for name in ("morton_orders", "slices_orders", "slice_loads", "full_balance_lineitem"):
        df = QUERIES[name](spark, sf)
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert "Cartesian" not in df._jdf.queryExecution().executedPlan().toString()
        for w in [x for x in plan.splitlines() if "Window [" in x]:
            # a window without partition columns stands over a table of at most as many rows as there are ranges
            assert "], [_r" in w or "_r#" in w, w
    scan = QUERIES["morton_orders"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "o_orderpriority" not in scan


def test_hilbert_tables_equal_the_fold(spark):
    """Keys from tables, as an expression and as columns, against the transform of coordinates; and their inverse."""
    for d, bits in ((3, 1), (3, 2), (3, 5), (4, 3)):
        g = datagen.mesh(spark, 1 << bits, d)
        cells = [F.col(f"g{i}") for i in range(d)]
        k = curves.with_hilbert(g.withColumn("code", curves.interleave(cells, bits)), "code", d, bits, "a").withColumn("b", curves.hilbert_key(cells, bits)).withColumn("c", curves._folded_key(cells, bits))
        back = curves.hilbert_cell(F.col("a"), d, bits)
        same = [x == y for x, y in zip(back, cells)]
        for cond in [F.col("a") == F.col("c"), F.col("b") == F.col("c"), *same]:
            assert k.where(~cond).isEmpty()


def test_prefix_ranges_grow_with_rows(spark, monkeypatch):
    """More rows have more ranges, up to those an expression tells apart and beyond; one key that overfills a range is split. Sums stay."""
    from curvebalance.plans import prefix

    df = spark.range(3000).select((F.col("id") * 7919 % 3000).alias("uid"), F.when(F.col("id") % 3 == 0, 5).otherwise(F.col("id") * 31 % 1000).cast("long").alias("key"), (F.col("id") % 5).alias("w"))
    want, at = {}, 0
    for r in sorted(df.collect(), key=lambda r: (r["key"], r["uid"])):
        want[r["uid"]] = at
        at += r["w"]
    for rows, cuts, over in ((250_000, 256, 8), (30, 256, 100), (30, 50, 8), (300, 256, 2)):
        monkeypatch.setattr(prefix, "RANGE_ROWS", rows)
        monkeypatch.setattr(prefix, "CUTS", cuts)
        monkeypatch.setattr(prefix, "OVERFULL", over)
        monkeypatch.setattr(prefix, "FIRST", 8)
        used = []
        kept = prefix.ranges
        monkeypatch.setattr(prefix, "ranges", lambda df, key, n: used.append(n) or kept(df, key, n))
        got = prefix.with_prefix(df, "key", "w", "uid", rank="rank").collect()
        monkeypatch.setattr(prefix, "ranges", kept)
        assert {r["uid"]: r["prefix"] for r in got} == want and sorted(r["rank"] for r in got) == list(range(3000))
        assert used == {(250_000, 256): [8], (30, 256): [8, 100], (30, 50): [8], (300, 256): [8, 10]}[rows, cuts]


def test_new_points_descend_to_their_leaf(spark):
    """A point inserted into a tree gets the leaf that planes lead to, also where no box is near; adjusted trees have the planes of their splits."""
    from curvebalance.operators import dynamic

    cfg = TreeConfig.of("midpoint", bucket_size=8)
    p = datagen.uniform(spark, 600, 2) if hasattr(datagen, "uniform") else spark.range(600).select(F.col("id").alias("uid"), *[(F.pmod(F.xxhash64("id", F.lit(i)), F.lit(10007)) / 10007.0).alias(f"c{i}") for i in range(2)], F.lit(1).cast("long").alias("w"))
    tree = kdtree.build(p, 2, cfg)
    m = tree.members.cache()
    planes = kdtree.split_planes(m, 2, cfg).cache()
    inner = {r["path"]: (r["dim"], r["value"]) for r in planes.collect()} | tree.top.inner
    for r in m.collect():  # the tree's own points
        at = 1
        while at in inner:
            d, v = inner[at]
            at = 2 * at + (r[f"c{d}"] > v)
        assert at == r["path"]
    new = spark.range(300).select((F.col("id") + 10_000).alias("uid"), *[(F.pmod(F.xxhash64("id", F.lit(9 + i)), F.lit(10007)) / 10007.0).alias(f"c{i}") for i in range(2)], F.lit(1).cast("long").alias("w"))
    got = dynamic.locate_leaf(kdtree.assign_top(new, tree.top), m, planes, 2).collect()
    assert len(got) == 300
    for r in got:
        at = 1
        while at in inner:
            d, v = inner[at]
            at = 2 * at + (r[f"c{d}"] > v)
        assert at == r["path"] and r["depth"] == kdtree.depth_of(r["path"])


@pytest.mark.parametrize("mode", ["full", "incremental"])
def test_dynamic_run_keeps_points_and_cuts_again(spark, mode):
    from curvebalance.operators import dynamic

    cfg = TreeConfig.of("midpoint", bucket_size=8)
    p = spark.range(800).select(F.col("id").alias("uid"), *[(F.pmod(F.xxhash64("id", F.lit(i)), F.lit(10007)) / 10007.0).alias(f"c{i}") for i in range(2)], F.lit(1).cast("long").alias("w"))

    def source(step):
        ops = p.where(F.col("uid").between(400 + 100 * step, 499 + 100 * step)).withColumn("op", F.lit("insert")).unionByName(p.where(F.col("uid").between(50 * step, 50 * step + 49)).withColumn("op", F.lit("delete")))
        return ops.withColumn("op_ts", F.lit(step)).withColumn("op_id", F.lit(0))

    members, trace = dynamic.run(p.where("uid < 400"), 2, cfg, 4, source, 3, adjust_every=2, policy="always", mode=mode)
    rows = members.collect()
    assert {r["uid"] for r in rows} == set(range(150, 700)) and len(rows) == 550
    loads = [sum(r["part"] == k for r in rows) for k in range(4)]
    assert max(loads) - min(loads) <= 1 and all(t["moved"] > 0 and t["rebalanced"] for t in trace)
    assert [(t["inserted"], t["deleted"]) for t in trace] == [(100, 50)] * 3 and trace[-1]["load_max"] == max(loads)


def test_policies_cut_one_order_again_without_writing_points(spark, monkeypatch):
    from curvebalance.plans import tables

    monkeypatch.setattr(amr, "BLOCK_ROWS", 4)
    monkeypatch.setattr(amr, "BLOCKS", 8)
    p = datagen.uniform(spark, 300, 2)
    p = amr.ordered(curves.keyed(p.unionByName(p.where("uid < 40")), 2, 8, box=[(0.0, 1.0)] * 2), 2)  # equal rows
    rows = sorted(map(tuple, p.select("rank", "c0", "c1").collect()))
    assert [r[0] for r in rows] == list(range(340))
    monkeypatch.setattr(tables, "snapshot", lambda *a: pytest.fail("a step writes the points"))
    sums = amr.block_sums(p, 2, range(4), 4, 0.4)
    for policy, known in (("always", None), ("amortised", sums), ("never", sums)):
        cut = None
        for s, x in enumerate(amr.run(p, 2, 5, 4, 0.4, policy, balance_cost=0.2, sums=known)):
            w = [8 if (a - s / 3) ** 2 + (b - s / 3) ** 2 <= 0.4 * 0.4 else 1 for _, a, b in rows]
            slices = [sum(w[:i]) * 5 // sum(w) for i in range(340)]
            cut = cut or slices
            assert x["loads"] == [sum(y for y, c in zip(w, cut) if c == k) for k in range(5)]
            assert x["cost"] == max(x["loads"]) / (sum(w) / 5)
            cut = slices if x["rebalanced"] else cut


def test_mesh_loop_refines_coarsens_and_smooths(spark):
    from curvebalance.operators import amr

    side, dims = 8, 2
    mesh = datagen.mesh(spark, side, dims).withColumn("v", (F.col("uid") % 5).cast("double"))
    blocks, trace = amr.mesh_run(mesh, dims, side, 4, 4, 0.4, "always")
    state = {(0, x, y): float((x * side + y) % 5) for x in range(side) for y in range(side)}
    for s in range(4):
        c = s / 3
        inside = {(x, y) for x in range(side) for y in range(side) if ((x + 0.5) / side - c) ** 2 + ((y + 0.5) / side - c) ** 2 <= 0.16}
        new = {}
        for (lv, x, y), v in state.items():
            up = (x, y) if lv == 0 else (x // 2, y // 2)
            if up in inside and lv == 0:
                new |= {(1, 2 * x + i, 2 * y + j): v for i in (0, 1) for j in (0, 1)}
            elif up in inside or lv == 0:
                new[lv, x, y] = v
            else:
                kids = [state[1, 2 * up[0] + i, 2 * up[1] + j] for i in (0, 1) for j in (0, 1)]
                new[0, *up] = sum(kids) / 4
        near = ((0, 0), (1, 0), (-1, 0), (0, 1), (0, -1))
        state = {}
        for lv, x, y in new:
            vals = [new[lv, x + i, y + j] for i, j in near if (lv, x + i, y + j) in new]
            state[lv, x, y] = sum(vals) / len(vals)
        assert trace[s]["blocks"] == len(state) and trace[s]["fine"] == sum(k[0] for k in state) and trace[s]["rebalanced"]
    got = {(r["level"], r["g0"], r["g1"]): r["v"] for r in blocks.collect()}
    assert got.keys() == state.keys() and all(abs(got[k] - state[k]) < 1e-9 for k in state)
    loads = [r["count"] for r in blocks.groupBy("part").count().collect()]
    assert max(loads) - min(loads) <= 1


def test_larger_caches_fault_less(spark, sf):
    from curvebalance.operators import external

    trace = [i * 7 % 30 for i in range(400)]
    assert [external.lru_faults(trace, c) for c in (1, 30)] == [400, 30] and external.lru_faults([1, 2, 1, 3, 2], 2) == 4
    rows = {r["capacity"]: r for r in QUERIES["page_cache"](spark, sf).collect()}
    n = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert rows[4]["reads"] == rows[64]["reads"] == n and 0 < rows[64]["faults"] <= rows[4]["faults"] <= n


def _cloud(spark, n, seed=5):
    c = np.random.default_rng(seed).random((n, 2))
    return points(spark, [(i, float(x), float(y), 1) for i, (x, y) in enumerate(c)], 2)


def test_cyclic_midpoint_paths_are_cells_of_the_unit_box(spark):
    rows = kdtree.build(_cloud(spark, 900), 2, TreeConfig.of("midpoint", dim_rule="cyclic", box="cell", bucket_size=20, k1=8)).members.collect()
    assert sorted(r["uid"] for r in rows) == list(range(900))
    leaves = {}
    for r in rows:
        lo, hi = [0.0, 0.0], [1.0, 1.0]
        for k, bit in enumerate(bin(r["path"])[3:]):
            m = (lo[k % 2] + hi[k % 2]) / 2
            (lo if bit == "1" else hi)[k % 2] = m
        assert all(lo[i] <= r[f"c{i}"] <= hi[i] for i in range(2)) and r["depth"] == len(bin(r["path"])) - 3
        leaves[r["path"]] = leaves.get(r["path"], 0) + 1
    assert max(leaves.values()) <= 20
    assert all(p >> k not in leaves for p in leaves for k in range(1, p.bit_length()))


@pytest.mark.parametrize("mode", ["histogram", "sample"])
def test_other_top_trees_keep_points_and_bound_leaves(spark, mode):
    rows = kdtree.build(_cloud(spark, 900), 2, TreeConfig.of("median_sort", bucket_size=20, k1=8, top_mode=mode, sample_frac=0.3)).members.collect()
    assert sorted(r["uid"] for r in rows) == list(range(900))
    leaves = {}
    for r in rows:
        leaves.setdefault(r["path"], []).append(r["top_id"])
    assert max(map(len, leaves.values())) <= 20 and len({t for x in leaves.values() for t in x}) > 1
    assert all(p >> k not in leaves for p in leaves for k in range(1, p.bit_length()))


def test_queries_are_binned_by_top_cell(spark):
    t = kdtree.build(_cloud(spark, 400), 2, TreeConfig.of("midpoint", bucket_size=20, k1=8))
    b = locate.bin_queries(_cloud(spark, 300, 6), t.top).select("uid", "top_id", F.spark_partition_id().alias("task")).collect()
    assert sorted(r["uid"] for r in b) == list(range(300))
    assert len({(r["top_id"], r["task"]) for r in b}) == len({r["top_id"] for r in b})


def test_cells_are_sliced_in_order():
    assert slicing.slice_cells([(4, 1), (5, 1), (6, 1), (7, 1)], 2) == {4: 0, 5: 0, 6: 1, 7: 1}
    assert slicing.slice_cells([(1, 9), (2, 1), (3, 2)], 3) == {1: 0, 2: 2, 3: 2}
    assert slicing.slice_cells([], 3) == {} and slicing.slice_cells([(1, 0)], 3) == {1: 0}


def test_concurrent_trees_share_no_part():
    trees = [(0, [1, 2]), (1, [3]), (2, [4]), (3, [4]), (5, [])]
    rounds = spmv.concurrent_trees(trees)
    assert sorted(o for r in rounds for o in r) == [0, 1, 2, 3, 5]
    leaves = dict(trees)
    for r in rounds:
        used = [p for o in r for p in {o, *leaves[o]}]
        assert len(used) == len(set(used))
    assert rounds == [[0, 3, 5], [1, 2]]


def test_tree_slices_of_a_matrix_have_equal_loads(spark):
    r = np.random.default_rng(8)
    cells = sorted({(int(a), int(b)) for a, b in r.integers(0, 40, (500, 2))})
    coo = spark.createDataFrame([(a, b, 1) for a, b in cells], "row long, col long, val long")
    got = graph.tree_partition(coo, 6, TreeConfig.of("midpoint", bucket_size=16, k1=4)).collect()
    assert sorted((x["row"], x["col"]) for x in got) == cells
    n = np.bincount([x["part"] for x in got], minlength=6)
    assert n.max() - n.min() <= 1


def test_intervals_with_owned_chunks(spark, sf):
    assert oracle.compare(QUERIES["spmv_intervals_owned"](spark, sf), ORACLE_SQL["spmv_intervals_owned"], oracle.connect(sf)) is None
