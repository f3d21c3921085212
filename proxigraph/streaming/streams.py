"""Streams: inserts into an index, queries against one, standing queries, windows and joins.

A micro-batch of new vectors is one batch insertion against the last committed version; versions
have folders of their own and the manifest is written last, so a batch that runs again writes the
same version again.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from proxigraph.functions.distance import expression
from proxigraph.operators.carriers import user_events
from proxigraph.operators.index import GraphIndex, SearchResult
from proxigraph.operators.model import PointSet
from proxigraph.runtime import ship


def stream_inserts(vectors: DataFrame, index: GraphIndex, path: str, checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    """Insert a stream of (id, vec): micro-batch b turns version b into version b + 1 under path."""
    index.save(path)
    base, metric = index.version, index.metric

    def commit(batch: DataFrame, number: int) -> None:
        before = GraphIndex.load(batch.sparkSession, path, base + number)
        fresh = batch.dropDuplicates(["id"]).join(before.rows.select("id"), "id", "left_anti")
        before.insert(PointSet(fresh, metric=metric)).save(path)

    return vectors.writeStream.foreachBatch(commit).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def stream_queries(queries: DataFrame, index: GraphIndex, k: int, sink, checkpoint: str, width: int = 64, trigger: dict | None = None) -> StreamingQuery:
    """Answer a stream of (id, vec); sink(results, stats, batch number) gets every micro-batch."""

    def answer(batch: DataFrame, number: int) -> None:
        found: SearchResult = index.search(PointSet(batch, metric=index.metric), k, width)
        sink(found.results, found.stats, number)

    return queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


#: A static side of a stream is broadcast up to so many rows.
MOST_STATIC = 100_000


def _static(points: PointSet, what: str) -> DataFrame:
    """The rows with a broadcast hint, after their number is checked."""
    rows = points.plain()
    if rows.limit(MOST_STATIC + 1).count() > MOST_STATIC:
        raise ValueError(f"{what}: more than {MOST_STATIC} static rows; use stream_queries over an index of them")
    return F.broadcast(rows)


class _Nearest(StatefulProcessor):
    """Keeps the k nearest arrivals of one standing query."""

    def __init__(self, k: int):
        self.k = k

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getListState("best", "id long, dist double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        have = {(float(d), int(i)) for i, d in self.best.get()} if self.best.exists() else set()
        for frame in rows:
            have |= set(zip(frame["dist"].astype(float), frame["id"].astype(int), strict=True))
        top = sorted(have)[: self.k]
        self.best.put([(i, d) for d, i in top])
        yield pd.DataFrame({"qid": [key[0]] * len(top), "id": [i for _, i in top], "dist": [d for d, _ in top], "rank": range(1, len(top) + 1)})

    def close(self) -> None:
        pass


def standing_queries(vectors: DataFrame, queries: PointSet, k: int, metric: str = "l2") -> DataFrame:
    """Stream of (qid, id, dist, rank): the k best so far of each standing query, sent again whenever
    it meets new vectors. queries is static; its size bounds the state."""
    ship(vectors.sparkSession)
    q = _static(queries, "standing queries").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    met = vectors.join(q).select("qid", F.col("id").cast("long").alias("id"), expression(metric, F.col("vec").cast("array<double>"), F.col("qvec")).alias("dist"))
    return met.groupBy("qid").transformWithStateInPandas(_Nearest(k), "qid long, id long, dist double, rank long", "Update", "None")


def user_vectors(events: DataFrame, window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Stream of per-user, per-window vectors; events later than `late` behind are dropped."""
    return user_events(events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late), window)


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, session start and end, events: activity sessions closed by a gap."""
    t = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    out = t.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("session_window.start").alias("begin"), F.col("session_window.end").alias("end"), "n")


def sliding_counts(events: DataFrame, window: str = "2 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    t = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    out = t.groupBy(F.window("ts", window, slide), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("begin"), "event_type", "n")


def near_alarms(vectors: DataFrame, base: PointSet, radius: float) -> DataFrame:
    """Stream of (qid, id, dist): arriving vectors within radius of a point of a static base, which is
    broadcast after its size is checked; larger ones go through stream_queries or index_alarms."""
    b = _static(base, "alarms").select(F.col("id").alias("bid"), F.col("vec").alias("bvec"))
    v = vectors.select(F.col("id").cast("long").alias("qid"), F.col("vec").cast("array<double>").alias("v"))
    return v.join(b).select("qid", F.col("bid").alias("id"), expression(base.metric, "bvec", "v").alias("dist")).filter(F.col("dist") <= radius)


def index_alarms(vectors: DataFrame, index: GraphIndex, radius: float, sink, checkpoint: str, width: int = 64, trigger: dict | None = None) -> StreamingQuery:
    """near_alarms against a base of any size: every micro-batch is a range search of its index, whose rows
    stay where they are; sink(results, batch number)."""

    def answer(batch: DataFrame, number: int) -> None:
        sink(index.range_search(PointSet(batch, metric=index.metric), radius, width, flood=True).results, number)

    return vectors.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def view_then_click(events: DataFrame, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a user's view and a click that follows it."""
    t = events.withColumn("ts", F.col("ts").cast("timestamp"))
    a = t.filter("event_type = 'view'").select(F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"), F.col("event_id").alias("view_id")).withWatermark("a_ts", late)
    b = t.filter("event_type = 'click'").select(F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"), F.col("event_id").alias("click_id")).withWatermark("b_ts", late)
    on = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select(F.col("a_user").alias("user_id"), "view_id", "click_id")


def first_arrivals(vectors: DataFrame, late: str = "1 hour") -> DataFrame:
    """Stream without repeated ids inside the watermark; vectors has id and ts."""
    return vectors.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"])


def read_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
