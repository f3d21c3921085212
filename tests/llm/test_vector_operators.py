import numpy as np
import pandas as pd
import pytest
from compare import database, rows
from pyspark.sql import functions as F

from proxigraph.llm import adaptive_scan, mtree, pareto_mix, queries, vector_cells

SCHEMA = "vec_id long, embedding array<float>, label int"


def brute(ids, x, k=20, every=20):
    out = {}
    for i, q in zip(ids, x, strict=True):
        if i % every == 0:
            s = x @ q
            s[ids == i] = -np.inf
            order = np.lexsort((ids, -s))[: min(k, len(ids) - 1)]
            out[int(i)] = (ids[order].tolist(), s[order])
    return out


def frame(spark, x):
    return spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(x)), "embedding": [v.tolist() for v in x], "label": 0}), SCHEMA)


@pytest.mark.parametrize("scale", ["unit", "mixed", "clustered"])
def test_recall_of_the_adaptive_scan(spark, scale):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((3000, 24))
    if scale == "unit":
        x /= np.linalg.norm(x, axis=1, keepdims=True)
    if scale == "mixed":
        x *= rng.uniform(0.2, 3.0, size=(3000, 1))
    if scale == "clustered":
        x = x * 0.1 + rng.standard_normal((30, 24))[rng.integers(30, size=3000)]
    x = x.astype(np.float32)
    df = frame(spark, x)
    got = adaptive_scan.search(df).toPandas()
    hit = total = 0
    for q, (ids, _) in brute(np.arange(3000), x.astype(float)).items():
        own = got[got.query_id == q].sort_values("rank")
        assert own["rank"].tolist() == list(range(1, len(own) + 1)) and (own.score.diff().dropna() <= 0).all()
        hit += len(set(ids) & set(own.vec_id))
        total += len(ids)
    assert hit / total >= 0.9
    scores = (x.astype(float)[got.query_id] * x.astype(float)[got.vec_id]).sum(axis=1)
    assert np.allclose(scores, got.score, rtol=0, atol=1e-12)


@pytest.mark.parametrize("kind,most_read", [("clustered", 0.45), ("given", 0.75)])
def test_tests_abandon_and_keep(spark, kind, most_read):
    """Candidates are given up early, on noise too (the given embeddings), and few neighbours with them."""
    rng = np.random.default_rng(0)
    if kind == "given":
        d = pd.read_parquet("/root/testdata/sf0.1/embeddings.parquet")
        x = np.stack(d.embedding.to_numpy()).astype(float)
    else:
        x = rng.standard_normal((20, 64))[rng.integers(20, size=2000)] + 0.3 * rng.standard_normal((2000, 64))
    ids = np.arange(len(x))
    known = vector_cells.Sample(ids, x, len(x), float((x ** 2).sum(axis=1).max()))
    lists = adaptive_scan.Lists(known)
    cell = adaptive_scan.Cell(lists, ids, x)
    at = ids[::20]
    found = cell.search(x[at], at, lists.terms(x[at], at, 20), 20)
    hit = 0
    for i, (rows, scores) in zip(at, found, strict=True):
        s = x @ x[i]
        s[i] = -np.inf
        hit += len(set(np.lexsort((ids, -s))[:20].tolist()) & set(cell.ids[rows].tolist()))
        assert len(rows) == 20 and np.allclose(scores, s[cell.ids[rows]])
    assert hit >= 0.95 * 20 * len(at)
    assert cell.read < most_read * cell.all


def odd(spark):
    nan, inf = float("nan"), float("inf")
    data = [
        (0, [1.0, 2.0], 1), (20, [0.5, 0.5], None), (3, None, 1), (4, [0.0, 0.0], 1), (40, [nan, 1.0], 1), (6, [inf, 1.0], 1), (7, [1.0, None], 1), (8, [1.0], 1), (None, [1.0, 1.0], 1),
        (9, [1.0, 2.0], 2), (10, [1.0, 2.0], 2), (11, [-3.0, 1.0], 3), (12, [2.0, 2.0], 1), (12, [2.0, 2.0], 1),
    ]
    return spark.createDataFrame(data, SCHEMA).withColumn("score", F.lit("x")).withColumn("id", F.lit(5))


def test_odd_vectors(spark):
    for op, use in ((adaptive_scan, {0: [1, 2], 20: [0.5, 0.5], 9: [1, 2], 10: [1, 2], 11: [-3, 1], 12: [2, 2]}), (mtree, {0: [64, 128], 20: [32, 32], 4: [0, 0], 9: [64, 128], 10: [64, 128], 11: [-192, 64], 12: [128, 128]})):
        ids = np.array(sorted(use))
        want = brute(ids, np.array([use[i] for i in ids.tolist()], dtype=float))
        got = op.search(odd(spark)).toPandas().sort_values(["query_id", "rank"])
        assert {q: (g.vec_id.tolist(), g.score.tolist()) for q, g in got.groupby("query_id")} == {q: (i, s.tolist()) for q, (i, s) in want.items()}
        none = spark.createDataFrame([], SCHEMA)
        assert op.search(none).count() == 0 and op.search(spark.createDataFrame([(0, [1.0], 1)], SCHEMA)).count() == 0


def test_tree_search_is_exact_and_avoids_work(spark):
    rng = np.random.default_rng(5)
    x = np.floor(64 * (rng.standard_normal((3000, 8)) * 0.1 + rng.standard_normal((20, 8))[rng.integers(20, size=3000)]))
    x[100:400] = x[100]
    ids = rng.permutation(10_000)[:3000].astype(np.int64)
    tree = mtree.Tree.build(ids, x, float((x ** 2).sum(axis=1).max()))
    by_id = np.argsort(ids)
    for i in range(0, 3000, 60):
        s = x @ x[i]
        s[i] = -np.inf
        order = np.lexsort((ids, -s))[:20]
        got = tree.search(x[i], int(ids[i]), 20)
        assert got[0].tolist() == ids[order].tolist() and got[1].tolist() == s[order].tolist()
    assert tree.avoided > 0 and tree.computed < 50 * 3000
    assert sorted(n for leaf, _, _, _, names in tree.pages.values() if leaf for n in names) == ids[by_id].tolist()


def test_radii_spare_shards(spark, monkeypatch):
    """On clusters a query visits few shards, with equal answers; too large components are refused."""
    rng = np.random.default_rng(8)
    x = (rng.standard_normal((2000, 8)) * 0.02 + 4 * rng.standard_normal((10, 8))[rng.integers(10, size=2000)]).astype(np.float32)
    monkeypatch.setattr(mtree, "SHARD_ROWS", 100)
    z = np.floor(64 * x.astype(float))
    visited = []
    plain = mtree.in_cells
    monkeypatch.setattr(mtree, "in_cells", lambda pages, routed, *rest: (visited.append(routed.count()), plain(pages, routed, *rest))[1])
    got = mtree.search(frame(spark, x)).toPandas().sort_values(["query_id", "rank"])
    for q, (ids, s) in brute(np.arange(2000), z).items():
        own = got[got.query_id == q]
        assert own.vec_id.tolist() == ids and own.score.tolist() == s.tolist()
    assert visited[0] < 0.5 * 100 * 20  # 100 queries, at least 20 shards
    with pytest.raises(ValueError):
        mtree.search(frame(spark, x * np.float32(1e8)))


def test_sql(spark, small_dir):
    con = database(small_dir)
    for name, text in queries.oracle_sql().items():
        got, want = rows(queries.queries()[name](spark, small_dir).toPandas()), rows(con.execute(text).df())
        assert got == want, name
    assert pareto_mix.SQL


def test_blocks_share_a_list_of_copies(spark):
    x = np.tile(np.array([[1.0, 0.0, 0.0, 0.5]], dtype=np.float32), (6000, 1))
    x[:200] = np.random.default_rng(2).standard_normal((200, 4))
    df = frame(spark, x)
    for op, z in ((adaptive_scan, x.astype(float)), (mtree, np.floor(64 * x.astype(float)))):
        got = op.search(df, every=500).toPandas().sort_values(["query_id", "rank"])
        for q, (ids, s) in brute(np.arange(6000), z, every=500).items():
            own = got[got.query_id == q]
            assert np.allclose(own.score, s) and own.vec_id.tolist() == ids
