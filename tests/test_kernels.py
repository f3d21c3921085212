import math

import numpy as np
import pytest
import reference_impl as R
from hypothesis import given, settings
from hypothesis import strategies as st

from proxigraph.functions.distance import block, gathered
from proxigraph.operators import kernels as K


def points(n, d=4, seed=0):
    return np.random.default_rng(seed).standard_normal((n, d))


def named(x):
    return {i: [float(v) for v in row] for i, row in enumerate(x)}


def lists(graph):
    return {i: {int(t) for t in row if t >= 0} for i, row in enumerate(graph.nbrs)}


def test_block_is_a_left_fold():
    x, q = points(40, 16), points(7, 16, 1)
    want = [[R.dist(a, b) for b in x.tolist()] for a in q.tolist()]
    assert np.array_equal(block(q, x), np.array(want))
    assert np.array_equal(gathered(q.T.copy(), np.arange(7)[:, None], x.T.copy(), np.arange(40)[None, :]), np.array(want))


def test_cosine_of_a_zero_vector_is_no_number():
    assert np.isnan(block(np.zeros((1, 3)), np.ones((1, 3)), "cosine")).all()


def test_schedule_inclusive_and_doubling():
    assert K.schedule(20, 5) == [(1, 2), (3, 6), (7, 12), (13, 18), (19, 20)]
    assert [b - a + 1 for a, b in K.schedule(30, 8, "doubling")] == [1, 1, 2, 4, 8, 8, 6]
    assert K.schedule(5, 2, "single") == [(1, 5)]
    assert K.schedule(0, 3) == []


@given(st.integers(0, 400), st.integers(1, 60), st.sampled_from(["inclusive", "doubling", "single", "sequential"]))
def test_schedule_covers_all_positions_once(n, cap, rule):
    batches = K.schedule(n, cap, rule)
    assert [p for a, b in batches for p in range(a, b + 1)] == list(range(1, n + 1))
    if rule == "inclusive":
        assert all(b - a <= cap for a, b in batches)
    if rule == "doubling":
        assert all(b - a < cap for a, b in batches)


def test_beam_search_equals_the_plain_one():
    x = points(50)
    g, _ = K.build_alpha(x.T.copy(), np.arange(50), 6, 10)
    out = {i: sorted(v) for i, v in lists(g).items()}
    for q in points(10, seed=3):
        want, comps = R.search(named(x), out, q.tolist(), g.start, 8)
        got = K.beam_search(g, q[:, None], 8, visited="exact")
        assert got.visited[0][got.visited[0] >= 0].tolist() == [v for _, v in want]
        assert got.distance[0][: len(want)].tolist() == [d for d, _ in want]
        assert got.comps[0] == comps and got.hops[0] == len(want)


def test_seen_gives_the_same_answers_for_fewer_distances():
    x = points(200, 8)
    g, _ = K.build_alpha(x.T.copy(), np.arange(200), 8, 16)
    q = points(30, 8, 5).T.copy()
    a, b = K.beam_search(g, q, 12, visited="exact"), K.beam_search(g, q, 12, visited="seen")
    assert np.array_equal(a.visited, b.visited) and (b.comps <= a.comps).all()


def test_lossy_table_may_only_revisit():
    x = points(200, 8)
    g, _ = K.build_alpha(x.T.copy(), np.arange(200), 8, 16)
    q = points(30, 8, 5).T.copy()
    a, b = K.beam_search(g, q, 6, visited="exact"), K.beam_search(g, q, 6, visited="lossy")
    assert (b.comps >= a.comps).all()
    assert np.array_equal(a.nearest(5)[0], b.nearest(5)[0])


def test_eps_visits_a_prefix():
    x = points(300, 6)
    g, _ = K.build_alpha(x.T.copy(), np.arange(300), 10, 20)
    q = points(20, 6, 7).T.copy()
    full = K.beam_search(g, q, 20, 5)
    for eps in (0.0, 0.1, 0.25):
        cut = K.beam_search(g, q, 20, 5, eps)
        for a, b in zip(full.visited, cut.visited, strict=True):
            b = b[b >= 0]
            assert b.tolist() == a[: len(b)].tolist()
    assert np.array_equal(K.beam_search(g, q, 20, 5, math.inf).visited, full.visited)


@pytest.mark.parametrize("alpha", [1.0, 1.2, 2.0])
def test_prune_equals_the_plain_one(alpha):
    x = points(60)
    for p in range(0, 60, 7):
        cand = np.array([i for i in range(60) if (i * 7 + p) % 3])
        d = np.array([R.dist(x[p].tolist(), x[c].tolist()) for c in cand])
        got, far = K.prune(x.T.copy(), np.array([p]), cand[None], d[None], 6, alpha)
        assert [c for c in got[0] if c >= 0] == R.prune(named(x), p, cand.tolist(), 6, alpha)
        kept = got[0][got[0] >= 0]
        for i, c in enumerate(kept):
            for j in kept[i + 1:]:
                assert alpha * R.dist(x[c].tolist(), x[j].tolist()) > R.dist(x[p].tolist(), x[j].tolist())


def test_prune_on_a_line():
    x = np.arange(8.0)[None, :]
    cand, d = np.arange(1, 8)[None], np.arange(1.0, 8.0)[None]
    assert K.prune(x, np.array([0]), cand, d, 7, 1.0)[0][0].tolist() == [1, -1, -1, -1, -1, -1, -1]
    assert K.prune(x, np.array([0]), cand, d, 7, 2.0)[0][0].tolist()[:4] == [1, 3, 7, -1]
    assert K.prune(x, np.array([0]), cand, d, 3, 1.0, keep_pruned=True)[0][0].tolist() == [1, 2, 3]
    assert K.prune(x, np.array([0]), cand, d, 3, 1.0, "nearest")[0][0].tolist() == [1, 2, 3]
    with pytest.raises(ValueError):
        K.prune(x, np.array([0]), cand, d, 3, 0.5)


@pytest.mark.parametrize("rule", ["inclusive", "doubling", "sequential", "single"])
def test_build_equals_the_plain_one(rule):
    x = points(55, 3, 2)
    ids = np.arange(55)
    g, _ = K.build_alpha(x.T.copy(), ids, 5, 9, 1.2, 0.1, rule)
    order = K.hashed_order(ids, 42)
    order = [int(p) for p in order if p != g.start]
    want = R.build(named(x), order, g.start, K.schedule(len(order), 6, rule), 5, 9, 1.2)
    assert lists(g) == want


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 70), st.integers(0, 5), st.booleans())
def test_graph_invariants(n, seed, copies):
    x = points(n, 3, seed)
    if copies and n:
        x = x[np.arange(n) // 3]
    for g in (K.build_alpha(x.T.copy(), np.arange(n), 4, 8)[0], K.build_tree_mst(x.T.copy(), np.arange(n), 3, 10), K.build_descent(x.T.copy(), np.arange(n), 2, 10, 5, 8)[0]):
        assert (g.degree() <= g.nbrs.shape[1]).all()
        for i, targets in lists(g).items():
            assert i not in targets
            assert all(0 <= t < n for t in targets)


def test_layers_are_nested_and_entry_is_on_top():
    x = points(300, 4)
    g, _ = K.build_layered(x.T.copy(), np.arange(300), 4, 16)
    sizes = [300] + [len(u) for u in g.upper]
    assert sizes == sorted(sizes, reverse=True) and len(sizes) > 2
    for below, above in zip(g.upper, g.upper[1:], strict=False):
        assert set(above) <= set(below)
    assert g.entry in g.upper[-1]
    got = K.layered_search(g, x[:20].T.copy(), 20, 1).nearest(1)[0][:, 0]
    assert (got == np.arange(20)).mean() > 0.9


def test_tree_leaves_partition_the_points():
    x = points(200, 3)
    for kind in ("pivots", "hyperplane"):
        leaves = K.tree_leaves(x.T.copy(), np.arange(200), 15, 1, kind)
        assert sorted(p for _, own in leaves for p in own) == list(range(200))
        assert max(len(own) for _, own in leaves) <= 15
    same = np.ones((3, 40))
    assert max(len(o) for _, o in K.tree_leaves(same, np.arange(40), 5)) <= 5


def test_spanning_trees():
    x = points(40, 3)
    full = K.leaf_mst(x.T.copy(), np.arange(40), None, 40)
    assert len(full) == 39 and abs(sum(e[2] for e in full) - R.prim(named(x))) < 1e-9
    bound = K.leaf_mst(x.T.copy(), np.arange(40), 10, 3)
    degree = np.bincount([e for a, b, _ in bound for e in (a, b)], minlength=40)
    assert degree.max() <= 3
    corners = np.array([[0.0, 0, 1, 1], [0, 1, 0, 1]])
    assert len(K.leaf_mst(corners, np.arange(4), None, 1)) == 2
    assert len(K.leaf_mst(corners, np.arange(4), None, 2)) == 3


def test_descent_rounds_equal_the_plain_ones():
    x = points(50, 3, 4)
    g = K.from_edges(x.T.copy(), *K.leaf_neighbours(x.T.copy(), np.arange(0, 50), 4), 4, None)
    keep = (np.arange(50)[:, None] * 7 + g.nbrs) % 3 != 0
    r, c = np.nonzero((g.nbrs >= 0) & keep)
    src, dst, d = r, g.nbrs[r, c], g.dists[r, c]
    want = {i: {int(t) for t in dst[src == i]} for i in range(50)}
    for rnd in range(3):
        known, before = (before if rnd else None), np.unique(src * 50 + dst)
        src, dst, d, _, _ = K.descent_round(x.T.copy(), src, dst, d, 4, None, np.arange(50), 42, rnd, block=7, known=known)
        want = R.descent_round(named(x), want, 4)
        assert {i: {int(t) for t in dst[src == i]} for i in range(50)} == want


def test_undirected_cap_keeps_the_least_draws():
    hub = np.zeros(30, dtype=np.int64)
    spokes = np.arange(1, 31)
    s, t, _ = K.undirected(hub, spokes, np.ones(30), 8, np.arange(31), 42, 0)
    assert (s == 0).sum() == 8 and (t == 0).sum() == 30


def test_islands_are_not_reachable():
    x = np.concatenate([points(10, 2), points(10, 2) + 100])
    g = K.from_edges(x.T.copy(), *K.leaf_neighbours(x.T.copy(), np.arange(20), 3), 3, None)
    assert not K.reach(g)[10:].any() and K.reach(g)[0]
