"""Beams that hold every vertex, without the steps."""

import time

import numpy as np
import pytest

from proxigraph.operators import kernels as K


def _sparse(rng, n, degree):
    """A graph in which not all vertices reach each other."""
    graph = K.empty_graph(rng.integers(0, 4, (3, n)).astype(float), degree)
    for p in range(n):
        near = rng.choice(n, rng.integers(0, degree + 1), replace=False)
        graph.nbrs[p, : len(near)] = near
    return graph


@pytest.mark.parametrize("visited", ["seen", "exact", "lossy"])
def test_exhausted_is_the_full_beam(visited):
    rng = np.random.default_rng(5)
    for degree in (1, 2, 6):
        graph = _sparse(rng, 60, degree)
        q, starts = rng.integers(0, 4, (3, 40)).astype(float), rng.integers(0, 60, 40)
        for own in (None, starts):
            a = K.beam_search(graph, q, 60, 7, visited=visited, starts=own)
            b = K.exhausted(graph, q, 7, own)
            (i, d), (j, e) = a.nearest(7), b.nearest(7)
            for row in range(40):
                real = np.isfinite(d[row])
                assert i[row][real].tolist() == j[row][np.isfinite(e[row])].tolist()
                assert d[row][real].tolist() == e[row][np.isfinite(e[row])].tolist()
            assert (a.hops == b.hops).all() and (a.comps == b.comps).all()
            assert ((a.visited >= 0).sum(axis=1) == b.processed).all()
            near = K.exhausted(graph, q, starts=own, radius=1.5)
            for row in range(40):
                inside = sorted(a.visited[row][(a.visited[row] >= 0) & (a.distance[row] <= 1.5)].tolist())
                assert sorted(near.visited[row][near.visited[row] >= 0].tolist()) == inside


def test_exhausted_takes_no_step_a_vertex():
    rng = np.random.default_rng(6)
    graph = K.empty_graph(rng.normal(size=(16, 20_000)), 8)
    graph.nbrs[:] = rng.integers(0, 20_000, (20_000, 8))
    began = time.process_time()
    found = K.exhausted(graph, rng.normal(size=(16, 1000)), 10)
    assert found.processed.min() > 19_000
    assert time.process_time() - began < 60  # the beam's steps take hours
