import numpy as np
import pytest
from pyspark.sql import functions as F

from proxigraph.operators import carriers, edges, exact, index, inverted, measures, rounds
from proxigraph.operators.model import PointSet
from proxigraph.plans import planner


@pytest.fixture(scope="module")
def data(spark, small_dir):
    return carriers.emb(spark, small_dir).split_queries(10)


def frame(spark, x):
    return PointSet(spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "id long, vec array<double>"))


def test_join_rounds_equal_the_kernel(spark, data):
    base, q = PointSet(data[0].df.filter("id < 28")), PointSet(data[1].df.filter("id < 40"))
    made, start = rounds.build_rounds(base, 4, 6, 1.2, 0.2)
    g = index.alpha_graph(base, 4, 6, 1.2, 0.2, joined=False)
    assert tuple(edges.fingerprint(made).first()) == g.fingerprint()
    a, b = rounds.search_rounds(made, base, q, 3, 6, start), g.search(q, 3, 6, visited="exact")
    order = ["qid", "rank"]
    assert a.results.orderBy(*order).collect() == b.results.select(a.results.columns).orderBy(*order).collect()
    assert a.stats.orderBy("qid").collect() == b.stats.orderBy("qid").collect()


@pytest.mark.parametrize("method,params", [
    ("alpha", {"degree": 8, "width": 16}), ("layered", {"m": 4, "width": 16}), ("tree_mst", {"trees": 4, "leaf": 40}), ("descent", {"trees": 3, "leaf": 40, "k": 10, "degree": 16}),
    ("hybrid", {"trees": 3, "leaf": 40, "degree": 8, "width": 16}),
])
def test_layout_does_not_matter_and_recall_is_high(spark, data, method, params):
    base, q = data
    a = index.BUILDERS[method](base, **params)
    b = index.BUILDERS[method](PointSet(base.df.repartition(5)), **params)
    assert a.fingerprint() == b.fingerprint()
    truth = exact.exact_knn(base, q, 5)
    ids = q.plain().select(F.col("id").alias("qid"))
    assert measures.mean_recall(truth, a.search(q, 5, 80).results, ids, 5).first()[0] >= 0.9
    split = index.BUILDERS[method](base, shard_rows=100, **params)
    assert split.shards.count >= 5
    assert measures.mean_recall(truth, split.search(q, 5, 60).results, ids, 5).first()[0] >= 0.9


def test_cells_route_queries(spark, data):
    base, q = data
    g = index.alpha_graph(base, 8, 16, shard_rows=100, shard_kind="cells")
    all_, some = g.search(q, 5, 60).stats, g.search(q, 5, 60, probe=1).stats
    assert some.agg(F.sum("dist_comps")).first()[0] < all_.agg(F.sum("dist_comps")).first()[0]


@pytest.mark.parametrize("n", [0, 1, 2, 5])
def test_tiny_tables(spark, n):
    x = np.array([[0.0, 0.0], [1.0, 0.3], [2.1, 0.1], [3.3, 0.5], [4.6, 0.2]])  # no ties, which alpha 1 would prune
    base = frame(spark, x[:n]) if n else PointSet(spark.createDataFrame([], "id long, vec array<double>"))
    q = frame(spark, x[:2] * 0.5)
    assert exact.exact_knn(base, q, 10).count() == 2 * n
    for build in index.BUILDERS.values():
        assert build(base).search(q, 10, 16).results.count() == 2 * n


def test_copies_and_ties(spark):
    base = frame(spark, [[1.0, 0.0]] * 5 + [[0.0, 1.0]] * 3)
    found = exact.exact_knn(base, frame(spark, [[1.0, 0.0]]), 6).orderBy("rank").collect()
    assert [r["id"] for r in found] == [0, 1, 2, 3, 4, 5]


def test_invalid_points_are_refused(spark):
    bad = PointSet(spark.createDataFrame([(0, [1.0, 2.0]), (1, None), (2, [1.0]), (3, [1.0, float("nan")]), (4, [3.0, 4.0]), (4, [3.0, 4.0])], "id long, vec array<double>"))
    assert {(r["id"], r["reason"]) for r in bad.invalid().collect()} == {(1, "null vector"), (2, "length"), (3, "component"), (4, "repeated id")}
    with pytest.raises(ValueError):
        bad.validate()


def test_width_below_k_is_refused(spark, data):
    with pytest.raises(ValueError):
        index.alpha_graph(PointSet(data[0].df.filter("id < 20"))).search(data[1], 10, 5)


def test_insert_save_load(spark, data, tmp_path):
    base, q = data
    g = index.alpha_graph(PointSet(base.df.filter("id < 200")), 8, 16)
    h = g.insert(PointSet(base.df.filter("id >= 200")))
    assert g.rows.count() + base.df.filter("id >= 200").count() == h.rows.count() and h.version == 1
    h.save(f"file://{tmp_path}/index")
    back = index.GraphIndex.load(spark, f"file://{tmp_path}/index", 1)
    assert back.fingerprint() == h.fingerprint()
    truth = exact.exact_knn(base, q, 5)
    ids = q.plain().select(F.col("id").alias("qid"))
    assert measures.mean_recall(truth, back.search(q, 5, 80).results, ids, 5).first()[0] >= 0.9


def test_range_variants(spark, data):
    base, q = data
    g = index.alpha_graph(base, 8, 16)
    true = {(r["qid"], r["id"]) for r in exact.exact_range(base, q, 1.15).collect()}
    beam = {(r["qid"], r["id"]) for r in g.range_search(q, 1.15, 16).results.collect()}
    flood = {(r["qid"], r["id"]) for r in g.range_search(q, 1.15, 16, flood=True).results.collect()}
    assert beam <= flood <= true
    assert {(r["qid"], r["id"]) for r in g.range_search(q, 1.15, 450, flood=True).results.collect()} == true


def test_probes_are_nested(spark, data):
    base, q = data
    i = inverted.InvertedIndex.build(base, 8, 2)
    truth = exact.exact_knn(base, q, 10)
    ids = q.plain().select(F.col("id").alias("qid"))
    got = [measures.mean_recall(truth, i.search(q, 10, p).results, ids).first()[0] for p in (1, 3, 8)]
    assert got == sorted(got) and got[-1] == 1.0


def test_range_recall_of_empty_truth(spark):
    truth = spark.createDataFrame([(1, 5)], "qid long, id long")
    ids = spark.createDataFrame([(1,), (2,)], "qid long")
    assert [measures.range_recall(truth, truth, ids, e).first()[0] for e in ("zero", "skip", "one")] == [0.5, 1.0, 1.0]


def test_planner(spark, data):
    base, _ = data
    assert planner.choose_engine(base).engine == "kernel" and planner.choose_engine(base, 100).shards == 5
    assert planner.choose_engine(base, whole=True, shard_rows=100).engine == "batches"
    unit = PointSet(base.df, metric="cosine")
    assert planner.normalise_metric(unit).metric == "l2"
    assert planner.normalise_metric(frame(spark, [[2.0, 0.0]])).metric == "l2"
    assert planner.normalise_metric(PointSet(frame(spark, [[2.0, 0.0]]).df, metric="cosine")).metric == "cosine"


def test_plans_prune_columns_and_use_group_limits(spark, data):
    base, q = data
    plan = exact.exact_knn(base, q, 3)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "label" not in plan


def test_global_trees_equal_the_kernel_and_the_baseline(spark, data):
    from proxigraph.operators import trees

    base = PointSet(data[0].df.filter("id < 150"))
    a = trees.tree_mst_edges(base, 3, 30)  # no vertex of this graph is out of reach, so nothing is joined to it
    b = trees.tree_mst_edges(base, 3, 30, parallel="trees")
    g = index.tree_mst_graph(base, 3, 30)
    assert tuple(edges.fingerprint(a).first()) == tuple(edges.fingerprint(b).first()) == g.fingerprint()
    copies = frame(spark, [[1.0, 2.0]] * 50 + [[3.0, 4.0]] * 5)
    assert trees.tree_mst_edges(copies, 2, 8).count() > 0


def test_global_descent_converges(spark, data):
    from proxigraph.operators import trees

    base = PointSet(data[0].df.filter("id < 120"))
    made, rounds_ = trees.descent_edges(base, 2, 40, 8, 16, delta=0.01, blocks=2)
    assert 0 < rounds_ < 20
    truth = {(r["src"], r["dst"]) for r in exact.exact_knn_graph(base, 3).collect()}
    assert len(truth & {(r["src"], r["dst"]) for r in made.collect()}) > 0.5 * len(truth)


@pytest.mark.parametrize("tasks", [1, 3])
def test_batches_equal_the_kernel(spark, data, monkeypatch, tasks):
    """Many tasks build one graph together; from the first batch on, with copies, and after a restart."""
    from proxigraph.operators import batches

    monkeypatch.setattr(batches, "SMALL", 40)
    monkeypatch.setattr(batches, "LEAST_POINTS", 1)
    base, q = data
    copies = base.plain().filter("id < 60").withColumn("id", F.col("id") + 100_000)
    points = PointSet(base.plain().filter("id < 300").unionByName(copies))
    a = index.alpha_graph(points, 8, 16, theta=0.1)
    b = index.alpha_graph(points, 8, 16, theta=0.1, engine="batches", tasks=tasks)
    assert a.fingerprint() == b.fingerprint() and b.build_cost().first()["dist_comps"] == a.build_cost().first()["dist_comps"]
    assert sorted(a.search(q, 5, 40).results.collect()) == sorted(b.search(q, 5, 40).results.collect())


def test_copies_are_one_vertex_and_all_are_found(spark):
    x = [[float(i % 7), float(i // 7)] for i in range(49)]
    rows = [(i, v) for i, v in enumerate(x)] + [(1000 + i, [3.0, 3.0]) for i in range(30)] + [(-5, [3.0, 3.0])]
    base = PointSet(spark.createDataFrame(rows, "id long, vec array<double>"))
    q = frame(spark, [[3.0, 3.1]])
    want = [(r["id"], r["dist"]) for r in exact.exact_knn(base, q, 20).orderBy("rank").collect()]
    for name, build in index.BUILDERS.items():
        g = build(base)
        assert [(r["id"], r["dist"]) for r in g.search(q, 20, 49).results.orderBy("rank").collect()] == want, name
        assert {(r["id"]) for r in g.range_search(q, 0.5, 10).results.collect()} == {24, -5, *range(1000, 1030)}
    # and where copies arrive later, of old vertices, of each other, and with smaller ids
    old = PointSet(base.df.filter("id >= 0 AND id < 1010"))
    for build in (index.alpha_graph, index.layered_graph):
        g = build(old).insert(PointSet(base.df.filter("id < 0 OR id >= 1010"))).insert(PointSet(spark.createDataFrame([(2000, [9.0, 9.0]), (2001, [9.0, 9.0])], "id long, vec array<double>")))
        assert [(r["id"], r["dist"]) for r in g.search(q, 20, 60).results.orderBy("rank").collect()] == want
        assert sorted(r["id"] for r in g.search(frame(spark, [[9.0, 9.0]]), 2, 60).results.collect()) == [2000, 2001]


@pytest.mark.parametrize("method", ["alpha", "layered", "tree_mst", "descent", "hybrid"])
def test_all_documents_can_be_reached(spark, small_dir, method):
    base, _ = carriers.doc(spark, small_dir.replace("0.001", "0.01")).split_queries(20)
    g = index.BUILDERS[method](base)
    start = g.rows.filter("start").first()["id"]
    assert edges.reachable(g.edges(), start).count() == g.rows.filter("id = rep").count()


def test_layered_inserts(spark, data):
    base, q = data
    g = index.layered_graph(PointSet(base.df.filter("id < 100")), 4, 16).insert(PointSet(base.df.filter("id >= 100")))
    truth = exact.exact_knn(base, q, 5)
    assert measures.mean_recall(truth, g.search(q, 5, 80).results, q.plain().select(F.col("id").alias("qid")), 5).first()[0] >= 0.9
    sizes = [r["count"] for r in g.rows.groupBy("level").count().orderBy("level").collect()]
    assert len(sizes) > 2 and sizes[0] > sizes[1]
    with_nothing = index.layered_graph(PointSet(base.df.filter("false"))).insert(base)
    assert with_nothing.rows.count() == base.df.count()


def test_a_search_does_not_move_the_index(spark, data, monkeypatch):
    from proxigraph.operators import resident

    base, q = data
    g = index.alpha_graph(base, 8, 16, shard_rows=100)
    seen = []
    monkeypatch.setattr(index, "settle", lambda df, name: (seen.append(df._jdf.queryExecution().executedPlan().toString()), index_settle(df, name))[1])
    want = sorted(g.search(q, 5, 40).results.collect())
    assert seen and "nbrs" not in seen[0] and "Exchange" in seen[0]
    # and in a store that only Spark opens
    monkeypatch.setattr(resident, "openable", lambda path: False)
    assert sorted(g.search(q, 5, 40).results.collect()) == want and "nbrs" in seen[-1]


index_settle = index.settle


def test_probes_and_a_hot_list(spark, data, monkeypatch):
    monkeypatch.setattr(inverted, "LIST_ROWS", 50)
    base, q = data
    i = inverted.InvertedIndex.build(base, 3, 2)
    assert int(i.first[-1]) > 6 and i.postings.groupBy("cell").count().agg(F.max("count")).first()[0] <= 110
    got = i.search(q, 10, 3)
    assert sorted(map(tuple, got.results.select("qid", "id", "dist", "rank").collect())) == sorted(map(tuple, exact.exact_knn(base, q, 10).select("qid", "id", "dist", "rank").collect()))
    assert got.stats.agg(F.min("dist_comps")).first()[0] == base.df.count() + 3
    plain = inverted.train_cells(base, 5, 1).collect()
    monkeypatch.setattr(inverted, "CENTROID_BYTES", 0)  # too many centroids to broadcast
    assert sorted(map(str, inverted.train_cells(base, 5, 1).collect())) == sorted(map(str, plain))


def test_queries_in_blocks(spark, data, monkeypatch):
    base, q = data
    want = sorted(exact.exact_knn(base, q, 7).collect())
    monkeypatch.setattr(exact, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(exact, "BLOCK_ROWS", 64)
    assert sorted(exact.exact_knn(base, q, 7).collect()) == want


def test_range_self_join_equals_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(2)
    x = rng.integers(0, 6, size=(160, 3)).astype(float)
    points = frame(spark, x)
    monkeypatch.setattr(exact, "BLOCK_ROWS", 20)
    first = {}
    for i, v in enumerate(map(tuple, x)):
        first.setdefault(v, i)
    reps = sorted(first.values())
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    want = {(a, b) for a in reps for b in reps if a < b and d[a, b] <= 1.5} | {(first[tuple(v)], i) for i, v in enumerate(x) if first[tuple(v)] != i}
    got = exact.range_self_join(points, 1.5).collect()
    assert {(r["u"], r["v"]) for r in got} == want and len(got) == len(want)


def test_residual_codes(spark, data):
    from proxigraph.operators import quantise

    base, q = data
    coded = quantise.CodedLists.build(base, 6, 2)
    truth = exact.exact_knn(base, q, 5)
    ids = q.plain().select(F.col("id").alias("qid"))
    got = [measures.mean_recall(truth, coded.search(base, q, 5, p, 60), ids, 5).first()[0] for p in (1, 6)]
    assert got[0] < got[1] and got[1] >= 0.7
    with pytest.raises(ValueError):
        quantise.ProductCodes.train(PointSet(base.df, metric="ip"))
