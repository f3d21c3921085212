"""Every vertex can be reached after an insert."""

import numpy as np

from proxigraph.operators import kernels as K


def test_arrivals_cut_nothing_off():
    lost = 0
    for seed in range(6):
        x = np.random.default_rng(seed).normal(size=(400, 24))
        graph = K.empty_graph(x.T.copy(), 3)
        old, fresh = np.flatnonzero(np.arange(400) % 3), np.flatnonzero(np.arange(400) % 3 == 0)
        own, _ = K.build_alpha(x[old].T.copy(), old, 3, 8)
        K.connect(own)
        graph.nbrs[old, :3], graph.dists[old, :3] = np.where(own.nbrs[:, :3] >= 0, old[own.nbrs[:, :3]], -1), own.dists[:, :3]
        graph.start = int(old[own.start])
        K.insert_points(graph, np.arange(400), fresh, 3, 8, 1.2)
        lost += int((~K.reach(graph)).sum())
    assert lost == 0
