import numpy as np
import pandas as pd

import corpus_pipeline
from proxigraph.llm import pareto_mix


def test_stages_take_effect(spark, small_dir):
    docs = spark.read.parquet(f"{small_dir}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "language", "near-duplicates", "mixing", "packing"]
    seen = [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, small_dir)
        assert out.columns == docs.columns
        rows = [tuple(r) for r in out.collect()]
        seen.append(len(rows))
        docs = spark.createDataFrame(rows, docs.schema)
    assert seen[1] < seen[0] and seen[2] <= seen[1] and seen[3] < seen[2]
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, small_dir).toPandas()
    assert packed.groupby("sequence_id").length.sum().max() <= 2048
    assert set(packed.doc_id) == {r["doc_id"] for r in docs.select("doc_id").distinct().collect()}
    run = corpus_pipeline.run(spark, small_dir).toPandas()
    key = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert sorted(map(tuple, run[key].to_numpy().tolist())) == sorted(map(tuple, packed[key].to_numpy().tolist()))


def test_empty_and_odd_documents(spark, tmp_path, small_dir):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    folder = f"file://{tmp_path}/t"
    spark.createDataFrame([], schema).write.parquet(f"{folder}/documents.parquet")
    spark.read.parquet(f"{small_dir}/labels.parquet").write.parquet(f"{folder}/labels.parquet")
    assert corpus_pipeline.run(spark, folder).count() == 0
    odd = f"file://{tmp_path}/o"
    rows = [(i, f"the words of text number {i} are here and there " * 4, "en", "a", 1) for i in range(12)] + [(20, None, None, None, None), (21, "", "en", "a", 0), (None, "no id is there", "en", None, 1)]
    spark.createDataFrame(rows, schema).write.parquet(f"{odd}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{odd}/labels.parquet")
    out = corpus_pipeline.run(spark, odd).toPandas()
    assert 20 not in set(out.doc_id) and 21 not in set(out.doc_id) and len(out)
    assert pareto_mix.SHARE == 1.5 and isinstance(out, pd.DataFrame) and np.isfinite(out.offset).all()
