"""Settled tables leave nothing behind but themselves."""

import os

from pyspark.sql import functions as F

from proxigraph.llm import shingle_sets
from proxigraph.runtime import settle, shared_dir


def _shuffle_files(spark) -> set[str]:
    dirs = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    return {f for d in dirs for _, _, names in os.walk(d) for f in names if f.startswith("shuffle_")}


def test_settle_leaves_no_shuffle_files(spark):
    counted = spark.range(10_000).repartition(3).groupBy((F.col("id") % 100).alias("k")).count()
    before = _shuffle_files(spark)
    confs = ("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "spark.sql.execution.arrow.maxRecordsPerBatch")
    set_ = [spark.conf.get(c) for c in confs]
    found = settle(counted, "counted")
    assert not _shuffle_files(spark) - before
    assert [spark.conf.get(c) for c in confs] == set_
    assert found.agg(F.sum("count")).first()[0] == 10_000


def test_similar_discards_its_postings_and_pairs(spark):
    texts = [" ".join(f"w{(i // 4) * 100 + j}" for j in range(60)) + (f" x{i}" if i % 4 else "") for i in range(40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    folder = shared_dir(spark).removeprefix("file://")
    before = set(os.listdir(folder))
    groups = {r["doc_id"]: r["component_id"] for r in shingle_sets.similar(docs, 5, 0.8).collect()}
    assert groups == {i: i // 4 * 4 for i in range(40)}
    left = {name.rsplit("-", 1)[0] for name in set(os.listdir(folder)) - before}
    assert not left & {"shingle-open", "shingle-pairs", "shingle-postings", "links", "large-star"}, left
