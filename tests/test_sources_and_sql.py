import numpy as np
from pyspark.sql import functions as F

from proxigraph.functions import sql
from proxigraph.operators import carriers, exact, index
from proxigraph.operators.model import PointSet
from proxigraph.sources import raw_vectors, tables


def test_raw_files_round_trip(spark, small_dir, tmp_path):
    p = carriers.emb8(spark, small_dir).plain()
    for kind in ("i8", "f32"):
        path = f"{tmp_path}/v.{kind}"
        assert raw_vectors.write_raw(p, path, kind) == p.count()
        back = raw_vectors.read_raw(spark, path, kind, rows_per_task=70)
        assert back.rdd.getNumPartitions() > 1
        a = back.select("id", F.col("vec").cast("array<double>").alias("vec")).orderBy("id").collect()
        assert a == p.orderBy("id").collect()
    empty = spark.createDataFrame([], "id long, vec array<double>")
    assert raw_vectors.write_raw(empty, f"{tmp_path}/none", "u8") == 0


def test_text_formats_round_trip(spark, small_dir, tmp_path):
    p = carriers.part(spark, small_dir)
    for fmt in ("parquet", "orc", "json", "csv"):
        path = f"file://{tmp_path}/{fmt}"
        tables.write_vectors(p, path, fmt)
        back = tables.read_vectors(spark, path, fmt)
        assert back.plain().orderBy("id").collect() == p.plain().orderBy("id").collect()


def test_runs_table(spark, tmp_path):
    from proxigraph.operators.measures import RUNS

    runs = spark.createDataFrame([("a", "m", {"width": "10"}, "recall", 0.5)], RUNS)
    for _ in range(2):
        tables.append_runs(runs, f"file://{tmp_path}/runs")
    assert tables.read_runs(spark, f"file://{tmp_path}/runs").collect() == runs.collect() * 2


def test_sql_functions(spark, small_dir, tmp_path):
    sql.register(spark)
    row = spark.sql("SELECT vec_l2(array(1D, 2D), array(4D, 6D)) a, vec_dot(array(1D, 2D), array(3D, 4D)) b, vec_cosine(array(0D), array(1D)) c, vec_l2_batch(array(1D, 2D), array(4D, 6D)) d").first()
    assert (row["a"], row["b"], row["c"], row["d"]) == (5.0, 11.0, None, 5.0)
    assert [tuple(r) for r in spark.sql("SELECT lo, hi FROM prefix_schedule(9, 4)").collect()] == [(1, 2), (3, 6), (7, 9)]


def test_table_function_searches_a_saved_index(spark, small_dir, tmp_path):
    sql.register(spark)
    base, q = carriers.emb(spark, small_dir).split_queries(10)
    index.alpha_graph(base, 8, 16, shard_rows=150).save(f"file://{tmp_path}/i")
    one = PointSet(q.df.filter("id = 10"))
    one.plain().createOrReplaceTempView("one")
    got = spark.sql(f"SELECT a.id FROM one, LATERAL ann_search(vec, '{tmp_path}/i/v0', 5, 450) a ORDER BY a.rank").collect()
    want = exact.exact_knn(base, one, 5).orderBy("rank").collect()
    assert [r["id"] for r in got] == [r["id"] for r in want]
    assert np.isfinite([r["dist"] for r in want]).all()
