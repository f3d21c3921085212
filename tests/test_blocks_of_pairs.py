"""Pairs within a leaf or a bin are met in blocks, by kernels."""

import numpy as np
from compare import database, rows

from proxigraph.operators import exact, trees
from proxigraph.operators.model import PointSet
from proxigraph.plans import relational_queries as R


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_leaves_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(trees, "LEAF_BLOCK", 40)
    x = np.random.default_rng(1).normal(size=(300, 6))
    points = PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"))
    leaves = trees.grow(points, 1, 2)
    out = trees.leaf_neighbours(leaves, points, 4)
    assert "zip_with" not in _plan(out)  # before: every pair of a leaf in one join, its distance an expression
    at = {(r["tree"], r["id"]): r["path"] for r in leaves.collect()}
    got = {}
    for r in out.collect():
        got.setdefault(r["src"], set()).add((r["dst"], round(r["dist"], 9)))
    for a in range(300):
        near = sorted((float(np.sqrt(((x[a] - x[b]) ** 2).sum())), b) for b in range(300) if b != a and any(at[t, a] == at[t, b] for t in (0, 1)))[:4]
        assert got[a] == {(b, round(d, 9)) for d, b in near}


def test_bins_in_blocks(spark, monkeypatch, small_dir):
    monkeypatch.setattr(exact, "BIN_ROWS", 30)
    out = R.range_join_pivot(spark, small_dir)
    assert "Join" not in _plan(out).split("MapInArrow")[0] and "MapInArrow" in _plan(out)
    want = database(small_dir).execute(R.ORACLES["range_join_pivot"]).df()
    assert rows(out.toPandas()) == rows(want)


def test_bins_hold_no_points(spark):
    none = PointSet(spark.createDataFrame([], "id long, vec array<double>"))
    some = spark.createDataFrame([(0, [1.0, 2.0])], "id long, vec array<double>")
    assert exact.range_by_pivot(none, PointSet(some), some.selectExpr("vec AS o"), 1.0).count() == 0
