from pyspark.sql import functions as F

from proxigraph.operators import carriers, exact, index
from proxigraph.operators.model import PointSet
from proxigraph.streaming import streams


def _files(df, path, parts):
    for i in range(parts):
        df.filter(F.col("id") % parts == i).coalesce(1).write.mode("append").parquet(path)


def test_stream_inserts_commit_versions(spark, small_dir, tmp_path):
    p = carriers.emb(spark, small_dir).plain().filter("id < 120")
    g = index.alpha_graph(PointSet(p.filter("id < 60")), 6, 12)
    _files(p.filter("id >= 60"), f"file://{tmp_path}/in", 2)
    prints = []
    for run in ("a", "b"):
        stream = streams.read_stream(spark, f"file://{tmp_path}/in", p.schema)
        streams.stream_inserts(stream, g, f"file://{tmp_path}/{run}", f"file://{tmp_path}/cp-{run}").awaitTermination()
        last = index.GraphIndex.load(spark, f"file://{tmp_path}/{run}", 2)
        assert last.rows.count() == 120
        prints.append(last.rows.select("id").distinct().count())
    assert prints == [120, 120]


def test_stream_queries_equal_batch(spark, small_dir, tmp_path):
    base, q = carriers.emb(spark, small_dir).split_queries(10)
    g = index.alpha_graph(PointSet(base.df.filter("id < 100")), 6, 12)
    _files(q.plain(), f"file://{tmp_path}/q", 2)
    got = []
    stream = streams.read_stream(spark, f"file://{tmp_path}/q", q.plain().schema)
    streams.stream_queries(stream, g, 3, lambda r, s, n: got.extend(r.select("qid", "id").collect()), f"file://{tmp_path}/cq", 16).awaitTermination()
    assert sorted(got) == sorted(g.search(q, 3, 16).results.select("qid", "id").collect())


def test_standing_queries_equal_exact(spark, small_dir, tmp_path):
    base, q = carriers.emb(spark, small_dir).split_queries(10)
    base, q = PointSet(base.df.filter("id < 100")), PointSet(q.df.filter("id < 40"))
    _files(base.plain(), f"file://{tmp_path}/v", 2)
    stream = streams.read_stream(spark, f"file://{tmp_path}/v", base.plain().schema)
    last = {}

    def keep(batch, number):
        for r in batch.collect():
            last.setdefault(number, {}).setdefault(r["qid"], []).append((r["rank"], r["id"]))

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = streams.standing_queries(stream, q, 4)
        out.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", f"file://{tmp_path}/cs").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    final = {}
    for n in sorted(last):
        final.update(last[n])
    want = exact.exact_knn(base, q, 4).collect()
    assert {(k, r, i) for k, v in final.items() for r, i in v} == {(r["qid"], r["rank"], r["id"]) for r in want}


def _event_stream(spark, small_dir, tmp_path):
    e = spark.read.parquet(f"{small_dir}/events.parquet")
    e.orderBy("ts").coalesce(1).write.parquet(f"file://{tmp_path}/e")
    return e, streams.read_stream(spark, f"file://{tmp_path}/e", e.schema)


def _drain(df, name, mode, tmp_path):
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"file://{tmp_path}/c-{name}").trigger(availableNow=True).start().awaitTermination()


def test_windows_and_joins_equal_batch(spark, small_dir, tmp_path):
    e, stream = _event_stream(spark, small_dir, tmp_path)
    _drain(streams.user_vectors(stream), "uv", "append", tmp_path)
    batch = carriers.user_events(e)
    got = {(r["user_id"], r["window_start"], tuple(r["vec"][:5])) for r in spark.table("uv").collect()}
    want = {(r["user_id"], r["window_start"], tuple(r["vec"][:5])) for r in batch.collect()}
    assert got and got <= want
    _drain(streams.view_then_click(stream, "6 hours"), "vc", "append", tmp_path)
    t = e.withColumn("ts", F.col("ts").cast("timestamp"))
    a = t.filter("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("x"), F.col("event_id").alias("view_id"))
    b = t.filter("event_type = 'click'").select(F.col("user_id").alias("w"), F.col("ts").alias("y"), F.col("event_id").alias("click_id"))
    want = a.join(b, F.expr("u = w AND y >= x AND y <= x + INTERVAL 6 hours")).select("view_id", "click_id").collect()
    assert sorted(spark.table("vc").select("view_id", "click_id").collect()) == sorted(want)
    _drain(streams.session_counts(stream), "sc", "append", tmp_path)
    assert spark.table("sc").count() > 0
    _drain(streams.sliding_counts(stream), "sl", "append", tmp_path)
    assert spark.table("sl").count() > 0


def test_alarms_and_first_arrivals(spark, small_dir, tmp_path):
    base = PointSet(carriers.emb(spark, small_dir).df.filter("id < 50"))
    twice = base.plain().unionByName(base.plain()).withColumn("ts", F.lit("2024-01-01 00:00:00").cast("timestamp"))
    twice.coalesce(1).write.parquet(f"file://{tmp_path}/t")
    stream = streams.read_stream(spark, f"file://{tmp_path}/t", twice.schema)
    _drain(streams.first_arrivals(stream), "fa", "append", tmp_path)
    assert spark.table("fa").count() == 50
    _drain(streams.near_alarms(stream, base, 0.0), "na", "append", tmp_path)
    assert spark.table("na").count() == 100
