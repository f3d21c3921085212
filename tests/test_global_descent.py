"""The descent graph by join rounds: pairs measured in blocks, leaves below small nodes, lost vertices joined."""

import numpy as np
import pytest

from proxigraph.operators import edges, exact, index, trees
from proxigraph.operators.model import PointSet


@pytest.fixture(scope="module")
def points(spark):
    x = np.random.default_rng(8).normal(size=(300, 6))
    x[250:] = x[0]
    return PointSet(spark.createDataFrame([(3 * i + 1, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>"))


def test_pairs_in_blocks(spark, points, monkeypatch):
    monkeypatch.setattr(edges, "PAIR_BLOCK", 70)
    rng = np.random.default_rng(9)
    pairs = spark.createDataFrame([(int(3 * a + 1), int(3 * b + 1)) for a, b in rng.integers(0, 310, (4000, 2))], "src long, dst long")
    got = edges.nearest_pairs(pairs.unionByName(pairs.limit(50)), points, 3)
    want = edges.nearest(edges.with_distance(pairs.distinct(), points), 3)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) != []


def test_known_ways_change_nothing(points):
    before = exact.exact_knn_graph(points, 5).filter("(src * 7 + dst) % 3 <> 0")
    after = edges.descent_round(before, points, 5, None)
    a, b = (sorted(map(tuple, edges.descent_round(after, points, 5, None, known=k).collect())) for k in (None, before))
    assert a == b != []


def test_leaves_below_small_nodes(points, monkeypatch):
    monkeypatch.setattr(trees, "NODE_ROWS", 100)
    for kind in ("pivots", "hyperplane"):
        rows = trees.grow_leaves(points, 2, 20, kind).collect()
        assert sorted((r["tree"], r["id"]) for r in rows) == [(t, 3 * i + 1) for t in range(2) for i in range(300)]
        sizes = {}
        for r in rows:
            sizes[r["tree"], r["path"]] = sizes.get((r["tree"], r["path"]), 0) + 1
        assert max(sizes.values()) <= 20


def test_lost_vertices_are_joined(spark, points):
    """Two halves without an edge between them, and a vertex without any."""
    made = exact.exact_knn_graph(points, 4).filter("(src < 400) = (dst < 400) AND src <> 7 AND dst <> 7")
    q = PointSet(points.df.filter("id % 5 = 0"))
    want = sorted((r["qid"], r["id"], r["dist"]) for r in exact.exact_knn(points, q, 10).collect())

    def answers(**how):
        return sorted((r["qid"], r["id"], r["dist"]) for r in index.fixed_graph(points, made, 1, **how).search(q, 10, 300).results.collect())

    assert answers() != want
    assert answers(joined=True) == want
