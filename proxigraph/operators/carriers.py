"""Vector carriers made of the given tables, and their query sets."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.functions.prng import draw
from proxigraph.operators.model import PointSet
from proxigraph.runtime import map_arrow, read_table


def _scaled(vec: str, scale: float, low: int, high: int, kind: str) -> Column:
    return F.transform(vec, lambda x: F.greatest(F.lit(low), F.least(F.lit(high), F.round(x.cast("double") * scale))).cast(kind))


def hashed_vectors(rows: DataFrame, dims: int, signed: bool = False, low: int = 0, high: int = 255, kind: str = "smallint") -> DataFrame:
    """rows (id, text, ...) with text turned into vec: counts of its blank-separated lower-cased tokens
    per bucket of their md5, or, signed, with a second part of the md5 as sign; clamped.

    An Arrow kernel: as an array expression this takes (tokens x dims) interpreted steps a text.
    """
    kept = [c for c in rows.columns if c != "text"]
    plain = rows.select(*kept, F.lower(F.coalesce("text", F.lit(""))).alias("text"))
    dtype = {"smallint": np.int16, "tinyint": np.int8}[kind]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        for batch in batches:
            texts = batch.column(len(kept)).to_pylist()
            out = np.zeros((len(texts), dims), dtype=np.int64)
            for i, text in enumerate(texts):
                hashes = []
                for t in text.split(" "):
                    if t:
                        h = known.get(t)
                        if h is None:
                            if len(known) > 500_000:
                                known.clear()
                            h = known[t] = int(hashlib.md5(t.encode("utf-8", "surrogatepass")).hexdigest()[:8], 16)
                        hashes.append(h)
                if hashes:
                    h = np.array(hashes)
                    w = np.where((h // dims) % 2 == 0, 1, -1) if signed else np.ones(len(h), dtype=np.int64)
                    np.add.at(out[i], h % dims, w)
            clamped = np.clip(out, low, high).astype(dtype)
            offsets = pa.array(np.arange(len(texts) + 1, dtype=np.int32) * dims)
            vec = pa.ListArray.from_arrays(offsets, pa.array(clamped.reshape(-1)))
            yield pa.RecordBatch.from_arrays([*(batch.column(j) for j in range(len(kept))), vec], [*kept, "vec"])

    schema = plain.select(*kept).schema.simpleString()[7:-1]
    return map_arrow(plain, run, f"{schema}, vec array<{kind}>")


def emb(spark: SparkSession, sf_dir: str) -> PointSet:
    t = read_table(spark, sf_dir, "embeddings")
    return PointSet(t.select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label"))


def emb8(spark: SparkSession, sf_dir: str) -> PointSet:
    t = read_table(spark, sf_dir, "embeddings")
    return PointSet(t.select(F.col("vec_id").alias("id"), _scaled("embedding", 127.0, -127, 127, "tinyint").alias("vec"), "label"))


def doc(spark: SparkSession, sf_dir: str, dims: int = 128) -> PointSet:
    t = read_table(spark, sf_dir, "documents")
    return PointSet(hashed_vectors(t.select(F.col("doc_id").alias("id"), "text", "lang", "source"), dims))


def bench_text(spark: SparkSession, sf_dir: str, dims: int = 128) -> PointSet:
    t = read_table(spark, sf_dir, "benchmark")
    return PointSet(hashed_vectors(t.select(F.col("item_id").alias("id"), "text"), dims))


def conv(spark: SparkSession, sf_dir: str, dims: int = 128) -> PointSet:
    """User turns, numbered conv_id * 1000 + turn."""
    t = read_table(spark, sf_dir, "conversations").filter("role = 'user'")
    return PointSet(hashed_vectors(t.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text"), dims))


def web(spark: SparkSession, sf_dir: str, dims: int = 100) -> PointSet:
    """Signed hashed token counts of tag-free pages, clamped to a signed byte."""
    t = read_table(spark, sf_dir, "pages")
    text = F.regexp_replace(F.coalesce("html", F.lit("")), "<[^>]*>", " ")
    return PointSet(hashed_vectors(t.select(F.col("page_id").alias("id"), text.alias("text")), dims, True, -127, 127, "tinyint"))


#: A key of lineitem that is unique in the given files.
NUM_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def num(spark: SparkSession, sf_dir: str) -> PointSet:
    """Five scaled numbers of each line item; the id is a draw of its key, unique in the given files."""
    t = read_table(spark, sf_dir, "lineitem")
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    key = F.conv(F.substring(F.md5(F.concat_ws(":", *[F.col(c).cast("string") for c in NUM_KEY])), 1, 15), 16, 10).cast("long")
    return PointSet(t.select(key.alias("id"), F.array(
        F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 100000.0, (F.col("l_discount") + 0.0) / 0.1, (F.col("l_tax") + 0.0) / 0.08, day / 2500.0,
    ).alias("vec")))


def part(spark: SparkSession, sf_dir: str) -> PointSet:
    t = read_table(spark, sf_dir, "part")
    return PointSet(t.select(F.col("p_partkey").alias("id"), F.array(F.col("p_size") / 50.0, (F.col("p_retailprice") - 900.0) / 100.0).alias("vec")))


def user_events(events: DataFrame, window: str = "1 day") -> DataFrame:
    """user_id, window_start and seven numbers of each user's events in each window."""
    kinds = ["click", "view", "purchase", "signup", "logout"]
    plain = dict(events.dtypes)["ts"] == "timestamp"  # a cast would lose a watermark
    t = events if plain else events.withColumn("ts", F.col("ts").cast("timestamp"))
    counts = [F.sum(F.when(F.col("event_type") == k, 1).otherwise(0)).alias(k) for k in kinds]
    rows = t.groupBy("user_id", F.window("ts", window)).agg(*counts, F.sum("value").alias("total"), F.avg("value").alias("mean"))
    return rows.select("user_id", F.col("window.start").alias("window_start"), F.array(*[F.col(k).cast("double") for k in (*kinds, "total", "mean")]).alias("vec"))


def ood(spark: SparkSession, sf_dir: str, dims: int = 64) -> PointSet:
    """Benchmark passages as signed hashed unit vectors: queries from another distribution than emb."""
    t = read_table(spark, sf_dir, "benchmark")
    raw = hashed_vectors(t.select(F.col("item_id").alias("id"), "text"), dims, True, -32767, 32767)
    size = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")))
    return PointSet(raw.withColumn("size", size).filter("size > 0").select("id", F.transform("vec", lambda x: x.cast("double") / F.col("size")).alias("vec")))


def sample_queries(points: PointSet, share: float, seed: int = 42) -> PointSet:
    return PointSet(points.df.filter(draw(seed, F.col(points.id)) < int(share * (1 << 32))), points.id, points.vec, points.metric)
