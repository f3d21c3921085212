"""What a worker holds: nothing of an earlier kernel, and few long texts at once."""

import gc
import os

import pyarrow as pa

from proxigraph.llm import token_ids
from proxigraph.runtime import KERNEL_ROWS, map_arrow


def test_another_kernel_frees_the_encoder(spark):
    path = token_ids.default_vocabulary()

    def encode(batches):
        for batch in batches:
            list(token_ids.encoder(path).encode(["some words"] * batch.num_rows))
            yield pa.RecordBatch.from_arrays([pa.array([os.getpid()]), pa.array([0])], ["pid", "held"])

    def held(batches):
        for _ in batches:
            yield pa.RecordBatch.from_arrays([pa.array([os.getpid()]), pa.array([sum(isinstance(x, token_ids.Encoder) for x in gc.get_objects())])], ["pid", "held"])

    ids = spark.range(0, 400, 1, 4)
    first = {r["pid"] for r in map_arrow(ids, encode, "pid long, held long").collect()}
    then = map_arrow(ids, held, "pid long, held long").collect()
    assert first & {r["pid"] for r in then}
    assert {r["held"] for r in then} == {0}


def test_a_result_that_the_caller_writes_comes_in_small_batches(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)

    def sizes(batches):
        for batch in batches:
            held = batch.column(0).buffers()[1].size // 8
            yield pa.RecordBatch.from_arrays([pa.array([held])], ["held"])

    try:
        spark.conf.set(name, "10000")
        found = map_arrow(spark.range(0, 10_000, 1, 1), sizes, "held long").collect()
        assert max(r["held"] for r in found) <= 2 * KERNEL_ROWS
        spark.conf.set(name, "100")
        map_arrow(spark.range(5), sizes, "held long")
        assert spark.conf.get(name) == "100"
    finally:
        spark.conf.set(name, before)
