"""The floor of recall holds on tables on which the first beam falls below it."""

import numpy as np

from proxigraph.operators import index
from proxigraph.operators.model import PointSet
from proxigraph.plans import method_queries as M


def test_effort_grows_until_the_recall_is_met(spark):
    x = np.random.default_rng(3).normal(size=(1500, 48))
    base, q = PointSet(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")).split_queries(30)
    search = M._beams(index.alpha_graph(base, 6, 12), q)
    tried = []

    def noted(width):
        tried.append(width)
        return search(width)

    assert not M._checked(search(12), base, q, 0.9).first()["enough"]
    rows = M._reaching(noted, 12, base, q, 0.9).collect()
    assert tried == [12 << i for i in range(len(tried))] and 1 < len(tried) < 8
    assert len(rows) == 50 and all(r["enough"] and r["sound"] and r["answers"] == 10 for r in rows)
