"""Candidates of product codes are re-ranked where their vectors lie."""

import numpy as np
import pytest

from proxigraph.operators import quantise
from proxigraph.operators.model import PointSet
from proxigraph.plans import method_queries as M


@pytest.mark.parametrize("rerank", [30, 10_000])
def test_rerank_in_cells(spark, monkeypatch, rerank):
    x = np.random.default_rng(4).normal(size=(700, 16))
    base, q = PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")).split_queries(10)
    settled = {}
    settle = quantise.settle

    def noted(df, name, *more):
        out = settle(df, name, *more)
        settled[name] = out.count()
        return out

    monkeypatch.setattr(quantise, "settle", noted)
    lists = quantise.CodedLists.build(base, 4, 2)
    codes = lists.codes
    coded = quantise.ProductCodes(codes.books).encode(base)
    for how in ("lists", "flat"):
        found = (lists.search(base, q, 5, 4, rerank) if how == "lists" else codes.search(coded, base, q, 5, rerank)).collect()
        got = {}
        for r in sorted(found, key=lambda r: (r["qid"], r["rank"])):
            got.setdefault(r["qid"], []).append((r["id"], r["dist"]))
        # before, every candidate left its cell, whatever k: 70 queries by 630 points here
        assert settled["rerank"] <= 70 * (rerank if rerank < 630 else 5 * 4)
        centers = {r["cell"]: np.array(r["centroid"]) for r in lists.lists.cells.collect()}
        own = {r["id"]: r["list"] for r in lists.lists.postings.select("id", "list").collect()}
        ids = np.array([i for i in range(700) if i % 10])
        away = {i: x[i] - (centers[own[i]] if how == "lists" else 0) for i in ids}

        def code(v):
            return np.concatenate([c[((p - c) ** 2).sum(axis=1).argmin()] for p, c in zip(np.split(v, len(codes.books)), codes.books, strict=True)])

        near = {i: code(away[i]) for i in ids}
        for a in range(0, 700, 10):
            table = sorted((round(float(((x[a] - (centers[own[i]] if how == "lists" else 0) - near[i]) ** 2).sum()), 9), i) for i in ids)[:rerank]
            want = sorted((float(np.sqrt(((x[a] - x[i]) ** 2).sum())), i) for _, i in table)[:5]
            assert [i for i, _ in got[a]] == [i for _, i in want]


def test_exhausted_lists_settle_answers_only(spark, monkeypatch, small_dir):
    settle, seen = quantise.settle, []

    def noted(df, name, *more):
        out = settle(df, name, *more)
        seen.append((name, out.count()))
        return out

    monkeypatch.setattr(quantise, "settle", noted)
    rows = M.pq_lists_exhausted(spark, small_dir).count()
    assert max(n for name, n in seen if name == "rerank") <= 8 * rows
