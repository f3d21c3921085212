"""The registered queries of the vector-search part."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.operators import carriers, index
from proxigraph.plans import method_queries, relational_queries, workloads


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alpha graph over the embeddings, searched by the held-out queries."""
    base, queries = carriers.emb(spark, sf_dir).split_queries(10)
    found = index.alpha_graph(base, 32, 64).search(queries, 10, 64).results
    return found.select("qid", "id", F.round("dist", 6).alias("dist"), F.col("rank").cast("long").alias("rank"))


def queries() -> dict:
    return method_queries.QUERIES | relational_queries.QUERIES | workloads.QUERIES


def oracle_sql() -> dict[str, str]:
    return method_queries.ORACLES | relational_queries.ORACLES
