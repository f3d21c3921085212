"""Distances that cannot matter are told by a sum in any order and need no left fold."""

import numpy as np

from proxigraph.functions import distance
from proxigraph.operators import kernels as K


def test_beyond_the_bound_is_infinite_and_the_rest_has_equal_bits():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(90, 33))
    x[7] = np.nan
    a, b = rng.integers(0, 90, (2, 5000))
    want = distance.gathered(x.T, a, x.T, b)
    most = rng.choice([0.0, 6.0, 8.0, np.inf], 5000)
    most[::50] = want[::50]  # ties with the bound are within it
    got = distance.gathered(x.T, a, x.T, b, most=most)
    inside = ~(want > most)
    assert np.array_equal(got[inside], want[inside], equal_nan=True)
    assert np.isinf(got[~inside & (want > most * (1 + 1e-8))]).all() and np.isinf(got).sum() > 1000


def test_a_descent_round_folds_few_pairs(monkeypatch):
    """With full lists most two-hop targets lie beyond the last edge; the rounds' edges are those without bounds."""
    rng = np.random.default_rng(5)
    x = rng.integers(0, 3, (400, 20)).astype(float)
    folded, plain = [], distance.gathered

    def noted(*args):
        d = plain(*args)
        folded.append((len(d), int(np.isfinite(d).sum())))
        return d

    def build():
        g, rounds = K.build_descent(x.T, np.arange(400), 2, 40, 6, 12)
        return g.nbrs.tolist(), g.dists.tolist(), g.comps, rounds

    monkeypatch.setattr(K, "gathered", lambda *args: plain(*args[:5]))
    want = build()
    monkeypatch.setattr(K, "gathered", noted)
    assert build() == want
    assert sum(f for _, f in folded) < 0.7 * sum(n for n, _ in folded)


def test_a_prune_folds_about_what_it_drops(monkeypatch):
    rng = np.random.default_rng(6)
    x = np.asfortranarray(rng.normal(size=(8, 300)))
    own, plain, folded = np.arange(50), distance.gathered, []
    cand = np.argsort(rng.random((50, 300)), axis=1)[:, :120]
    far = plain(x, own.repeat(120), x, cand.ravel()).reshape(cand.shape)
    monkeypatch.setattr(K, "gathered", lambda *args: plain(*args[:5]))
    want = K.prune(x, own, cand, far, 16, 1.2)

    def noted(*args):
        d = plain(*args)
        folded.append(int(np.isfinite(d).sum()))
        return d

    monkeypatch.setattr(K, "gathered", noted)
    got = K.prune(x, own, cand, far, 16, 1.2)
    assert (got[0] == want[0]).all() and (got[1] == want[1]).all()
    assert sum(folded) <= cand.size  # each candidate is dropped once at most
