import pytest
from compare import database, rows

import __spark_entry__ as entry
from proxigraph.plans import registry, workloads

ORACLES = registry.oracle_sql()


@pytest.fixture(scope="module")
def con(small_dir):
    return database(small_dir)


def test_entry(spark):
    out = entry.entry(spark)
    assert out.columns == ["qid", "id", "dist", "rank"] and out.count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_its_sql(spark, con, small_dir, name):
    got = rows(registry.queries()[name](spark, small_dir).toPandas())
    want = rows(con.execute(ORACLES[name]).df())
    assert got[0] == want[0]
    assert got[1] == want[1]


def test_only_workloads_have_no_sql():
    assert {n for n in registry.queries() if n not in ORACLES} == set(workloads.QUERIES)
