"""Hash buckets: candidates meet in cells, and only answers leave them."""

import numpy as np
import pytest
from compare import database, rows

from proxigraph.operators import hashing
from proxigraph.operators.model import PointSet
from proxigraph.plans import method_queries as M


def _points(spark, n=900, dims=12):
    x = np.random.default_rng(8).normal(size=(n, dims))
    x[: n // 3] = x[0]  # a bucket of copies
    return PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"))


@pytest.mark.parametrize("kind", ["sign", "cross"])
@pytest.mark.parametrize("most", [None, 25])
def test_cells_meet_what_a_join_of_buckets_meets(spark, monkeypatch, kind, most):
    monkeypatch.setattr(hashing, "CELL_ROWS", 64)
    base, q = _points(spark).split_queries(10)
    tables, bits, probes = 3, 4, 2
    found = hashing.HashIndex.build(base, kind, tables, bits).search(q, 5, probes, most)
    own, asked = (hashing.buckets(p, tables, bits, m, kind).toPandas() for p, m in ((base, 1), (q, probes)))
    met = asked.merge(own, on=["tbl", "bucket"], suffixes=("_q", ""))
    met = met.groupby(["id_q", "id"]).agg({"probe_q": "min", "vec_q": "first", "vec": "first"}).reset_index().sort_values(["id_q", "probe_q", "id"])
    met = met if most is None else met.groupby("id_q").head(most)
    want = {}
    for r in met.itertuples():
        d = 0.0
        for a, b in zip(r.vec, r.vec_q, strict=True):
            d += (a - b) * (a - b)
        want.setdefault(r.id_q, []).append((float(np.sqrt(d)), r.id))
    got = {}
    for r in found.results.orderBy("qid", "rank").collect():
        got.setdefault(r["qid"], []).append((r["dist"], r["id"]))
    assert got == {i: sorted(v)[:5] for i, v in want.items()}
    assert {r["qid"]: r["dist_comps"] for r in found.stats.collect() if r["dist_comps"]} == {i: len(v) for i, v in want.items()}


def test_no_row_a_pair(spark, monkeypatch, small_dir):
    """Only answers are settled: at most k a query and cell (before: a row, with both vectors, a pair that meets)."""
    seen = []
    settle = hashing.settle

    def noted(df, name, *more):
        out = settle(df, name, *more)
        if name == "candidates":
            seen.append(out.count())
        return out

    monkeypatch.setattr(hashing, "settle", noted)
    con = database(small_dir)
    n = con.execute("SELECT count(*) FROM embeddings WHERE vec_id % 10 = 0").fetchone()[0]
    got = M.lsh_multiprobe(spark, small_dir).toPandas()
    assert rows(got) == rows(con.execute(M.ORACLES["lsh_multiprobe"]).df())
    assert seen and seen[0] <= n * 2 * 4  # a row a table and probe


def test_library_meets_in_cells(spark, monkeypatch, small_dir):
    def fail(*a, **b):
        raise AssertionError("a row a pair")

    from pyspark.ml.feature import BucketedRandomProjectionLSHModel

    base, q = M._emb(spark, small_dir)
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    p, o = (s.plain().select("id", array_to_vector("vec").alias("x")) for s in (base, q))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", bucketLength=2.0, numHashTables=4, seed=42).fit(p)
    met = model.approxSimilarityJoin(o, p, float("inf"), "dist").selectExpr("datasetA.id AS qid", "datasetB.id AS id", "dist").toPandas()
    want = {i: set(g.nsmallest(10, "dist").id) for i, g in met.groupby("qid")}
    monkeypatch.setattr(BucketedRandomProjectionLSHModel, "approxSimilarityJoin", fail)
    got = hashing.library_lsh(base, q, 10).toPandas()
    assert {i: set(g.id) for i, g in got.groupby("qid")} == want


@pytest.mark.parametrize("most", [1, 25, 140, 300])
def test_cut_sends_only_the_last_range(spark, monkeypatch, most):
    """A bound on the candidates makes a cell return k of them and those of one range of ids (before: as many as the bound
    from every bucket, so all pairs as the bound grows)."""
    x = np.random.default_rng(11).normal(size=(1200, 12))
    x[5] = np.nan
    base, q = PointSet(spark.createDataFrame([(7 * i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")).split_queries(10)
    monkeypatch.setattr(hashing, "RANGE_ROWS", 32)
    monkeypatch.setattr(hashing, "CELL_ROWS", 256)
    seen = []
    settle = hashing.settle

    def noted(df, name, *more):
        out = settle(df, name, *more)
        if name == "candidates":
            seen.append(max(r["n"] for r in out.selectExpr("qid", "size(ids) AS n").groupBy("qid").agg({"n": "sum"}).toDF("qid", "n").collect()))
        return out

    monkeypatch.setattr(hashing, "settle", noted)
    tables, bits, probes = 3, 4, 3
    index = hashing.HashIndex.build(base, "cross", tables, bits)
    spent: list[str] = []
    found = index.search(q, 5, probes, most, spent)
    own, asked = (hashing.buckets(p, tables, bits, m, "cross").toPandas() for p, m in ((base, 1), (q, probes)))
    met = asked.merge(own, on=["tbl", "bucket"], suffixes=("_q", ""))
    met = met[met.id != 35].groupby(["id_q", "id"]).agg({"probe_q": "min"}).reset_index().sort_values(["id_q", "probe_q", "id"]).groupby("id_q").head(most)
    want = {i: sorted((float(np.sqrt(((x[j // 7] - x[i // 7]) ** 2).sum())), j) for j in g.id)[:5] for i, g in met.groupby("id_q")}
    got = {}
    for r in found.results.orderBy("qid", "rank").collect():
        got.setdefault(r["qid"], []).append((r["dist"], r["id"]))
    assert {i: [j for _, j in v] for i, v in got.items()} == {i: [j for _, j in v] for i, v in want.items()}
    assert np.allclose([d for i in sorted(got) for d, _ in got[i]], [d for i in sorted(got) for d, _ in want[i]])
    visits = tables * probes * max([1, *(many for _, many in index.large.values())])
    assert seen[0] <= 5 * visits + 2 * 32 * 2 and len(spent) == 3
