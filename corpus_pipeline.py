"""The corpus pipeline: five stages, each written as Parquet and read again by the next one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from proxigraph.llm import packing, pareto_mix, ppm_langid, simhash_pivots, toxicity_ftrl
from proxigraph.runtime import read_table, settle

#: Documents are near-duplicates from this Jaccard similarity of their sets of so many words in a row on.
SHINGLE_WORDS = 5
LEAST_SIMILARITY = 0.8


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents predicted toxic; the model learns from this corpus and its labels."""
    model = toxicity_ftrl.fit(docs, read_table(spark, sf_dir, "labels"))
    return toxicity_ftrl.score(docs, model).filter("predicted = 0").select(*docs.columns)


def drop_unknown_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents without a letter, and those that no learnt language codes in half of eight bits
    a byte, as strings of digits, keys or shouted fragments."""
    return ppm_langid.predict(docs, ppm_langid.fit(docs)).filter(ppm_langid.recognised()).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of every group of near-duplicates."""
    return simhash_pivots.keep_one(docs, shingle_words=SHINGLE_WORDS, least_jaccard=LEAST_SIMILARITY)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or leaves out documents so that the sources reach their target weights."""
    return pareto_mix.repeated(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places every document's tokens in sequences of fixed size."""
    return packing.pack_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("language", drop_unknown_language),
    ("near-duplicates", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = settle(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs


#: Neither the classifiers nor the tokens can be expressed in SQL; tests compare with plain versions.
ORACLE_SQL = None
