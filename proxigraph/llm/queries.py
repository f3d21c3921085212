"""The registered queries of the operators in this subpackage, and the SQL of those that have any."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.runtime import fresh_path, read_table


def op1_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import adaptive_scan as op

    return op.search(read_table(spark, sf_dir, "embeddings"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import simhash_pivots as op

    found = op.near_duplicates(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", op.hex_fingerprint().alias("fingerprint"), "component_id")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import toxicity_ftrl as op

    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    model = op.fit(docs, read_table(spark, sf_dir, "labels"))
    return op.score(docs, model).select("doc_id", (op.fold() == 0).alias("held_out"), "score", "predicted")


def op4_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import html_templates as op

    return op.extract(read_table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import packing as op

    return op.pack_documents(read_table(spark, sf_dir, "documents"))


def op6_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import mtree as op

    return op.search(read_table(spark, sf_dir, "embeddings"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import token_files as op

    folder = fresh_path(spark, "token-files")
    op.write(read_table(spark, sf_dir, "documents"), folder)
    return op.read(spark, folder)


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import license_patience as op

    return op.scan(read_table(spark, sf_dir, "documents"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import pareto_mix as op

    docs = read_table(spark, sf_dir, "documents").select("doc_id", "source", op.word_count().alias("size"))
    return op.mix(docs).select("doc_id", "size", "source_size", "target", "taken")


def op10_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    from proxigraph.llm import ppm_langid as op

    docs = read_table(spark, sf_dir, "documents")
    model = op.fit(docs)
    return op.predict(docs.select("doc_id", "text"), model).select("doc_id", (op.fold() == 0).alias("held_out"), "lang_pred", "score")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {f.__name__: f for f in (op1_ann, op2_simhash, op3_toxicity, op4_html, op5_packing, op6_topk, op7_token_files, op8_licenses, op9_mixing, op10_langid, pipeline)}


def oracle_sql() -> dict[str, str]:
    from proxigraph.llm import mtree, pareto_mix

    return {"op6_topk": mtree.SQL, "op9_mixing": pareto_mix.SQL}
