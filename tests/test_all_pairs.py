"""All pairs by blocks equal those of the SQL function, odd vectors included."""

import numpy as np
import pytest

from proxigraph.functions.sql import register
from proxigraph.operators import exact
from proxigraph.operators.model import PointSet
from proxigraph.plans.relational_queries import sql_vector_functions, vector_function_pairs


def _sets(spark):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(size=3).tolist()) for i in range(1, 60)]
    rows += [(61, None), (62, [1.0, 2.0]), (63, [1.0, None, 2.0]), (64, [float("nan"), 1.0, 1.0]), (65, [float("inf"), 0.0, 1.0]), (66, []), (7, [0.0, 0.0, 1.0])]
    rows += [(70, None), (80, [1.0]), (90, [None, 1.0, 1.0]), (100, [float("inf"), 0.0, 1.0]), (110, [])]
    return PointSet(spark.createDataFrame(rows, "id long, vec array<double>")).split_queries(10)


def _rows(df):
    return sorted(repr(tuple(r)) for r in df.select("qid", "id", "dist").collect())


@pytest.mark.parametrize("most", [1 << 26, 0])
def test_all_pairs_are_those_of_the_function(spark, monkeypatch, most):
    monkeypatch.setattr(exact, "BROADCAST_BYTES", most)
    monkeypatch.setattr(exact, "BIN_ROWS", 20)
    register(spark)
    base, q = _sets(spark)
    got = _rows(vector_function_pairs(base, q))
    base.plain().createOrReplaceTempView("all_p")
    q.plain().createOrReplaceTempView("all_q")
    assert got == _rows(spark.sql("SELECT q.id AS qid, p.id AS id, round(vec_l2(p.vec, q.vec), 6) AS dist FROM all_p p CROSS JOIN all_q q"))
    assert len(got) == base.df.count() * q.df.count()


def test_no_row_interprets_a_fold_for_each_pair(spark, small_dir):
    """All vectors of the tables are even, and none of their pairs is joined as rows."""
    plan = sql_vector_functions(spark, small_dir)
    assert plan.count() == 22_500
    assert "MapInArrow" in plan._jdf.queryExecution().executedPlan().toString()


def test_no_points_no_pairs(spark):
    register(spark)
    none = PointSet(spark.createDataFrame([], "id long, vec array<double>"))
    assert vector_function_pairs(none, none).count() == 0
    base, q = _sets(spark)
    assert vector_function_pairs(base, none).count() == vector_function_pairs(none, q).count() == 0
