"""Flat token files: unsigned ids of all documents in a row, and where each document begins.

A dataset is a folder of shards in ascending order of the documents' ids. Shard k has
`<k>.bin`, the ids (2 bytes each if the vocabulary allows, else 4, little-endian), `<k>.off`, the
signed 64-bit position in the shard of each document's first id and of the end, and `<k>.doc`, the
signed 64-bit document ids. `manifest.json` lists the shards with the prefix sums of their documents
and ids, so that any document's global position is its shard's base plus its offset. Shards are
memory-mapped where the folder is on a mounted file system, else read by range.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.llm import token_ids
from proxigraph.runtime import map_arrow, settle

END_ID = 2
#: Stands for a null document id in `.doc` files.
NULL_DOC = -(1 << 63)


def _filesystem(uri: str):
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def _array(uri: str, dtype) -> np.ndarray:
    """The file's numbers, memory-mapped if it is on a mounted file system."""
    from pyarrow import fs

    system, path = _filesystem(uri)
    if isinstance(system, fs.LocalFileSystem):
        return np.memmap(path, dtype=dtype, mode="r") if os.path.getsize(path) else np.empty(0, dtype)
    with system.open_input_file(path) as f:
        return np.frombuffer(f.read_buffer(), dtype=dtype)


def write(docs: DataFrame, folder: str, end_id: int = END_ID, vocabulary: str | None = None) -> dict:
    """Encode every whole text (null: empty), append end_id, write the dataset; returns its manifest.

    Documents are in ascending doc_id order, null ids first, rows of one id in order of their text. A
    task writes its shard under a name of its own and then renames it, so a task that runs again
    replaces the whole shard. An empty table gives a manifest without shards.
    """
    path = vocabulary or token_ids.default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context = TaskContext.get()
        encoder = token_ids.encoder(path)
        wide = max(encoder.tokenizer.get_vocab_size(), end_id + 1) > 1 << 16
        dtype = np.dtype("<u4" if wide else "<u2")
        system, root = _filesystem(folder)
        system.create_dir(root, recursive=True)
        shard = f"{context.partitionId():06d}"
        own = f"{root}/_{shard}-{context.taskAttemptId()}"
        sizes, names = [], []
        out = None
        for batch in batches:
            keys = batch.column(0).to_pylist()
            for lo, hi, ids, lengths in encoder.encode(batch.column(1).to_pylist()):
                out = out or system.open_output_stream(f"{own}.bin")
                full = np.insert(ids, np.cumsum(lengths), end_id).astype(dtype)
                out.write(full.tobytes())
                sizes.append(lengths + 1)
                names += [NULL_DOC if k is None else k for k in keys[lo:hi]]
        if out is None:
            return
        out.close()
        offsets = np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype("<i8")
        for kind, numbers in (("off", offsets), ("doc", np.array(names, dtype="<i8"))):
            with system.open_output_stream(f"{own}.{kind}") as f:
                f.write(numbers.tobytes())
        for kind in ("bin", "off", "doc"):
            system.move(f"{own}.{kind}", f"{root}/{shard}.{kind}")
        yield pa.RecordBatch.from_pydict({"shard": [shard], "first": [names[0]], "docs": [len(names)], "ids": [int(offsets[-1])], "bytes_per_id": [dtype.itemsize]})

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(F.col("doc_id").asc_nulls_first())
    ordered = ordered.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    done = settle(map_arrow(ordered, run, "shard string, first long, docs long, ids long, bytes_per_id long"), "token-shards")
    shards, at, first_doc = [], 0, 0
    for r in sorted(done.collect(), key=lambda r: (r["first"], r["shard"])):  # one short row per shard
        shards.append({"name": r["shard"], "docs": r["docs"], "ids": r["ids"], "first_id": at, "first_doc": first_doc, "bytes_per_id": r["bytes_per_id"]})
        at, first_doc = at + r["ids"], first_doc + r["docs"]
    manifest = {"ids": at, "docs": first_doc, "end_id": end_id, "shards": shards}
    system, root = _filesystem(folder)
    system.create_dir(root, recursive=True)
    with system.open_output_stream(f"{root}/manifest.json") as f:
        f.write(json.dumps(manifest).encode())
    return manifest


def read_manifest(folder: str) -> dict:
    system, root = _filesystem(folder)
    with system.open_input_file(f"{root}/manifest.json") as f:
        return json.loads(f.read())


def read(spark: SparkSession, folder: str, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the files (and its ids as an array)."""
    shards = [(s["name"], s["first_id"], s["bytes_per_id"]) for s in read_manifest(folder)["shards"]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, base, width in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                ids = _array(f"{folder}/{name}.bin", f"<u{width}")
                offsets = _array(f"{folder}/{name}.off", "<i8")
                docs = _array(f"{folder}/{name}.doc", "<i8")
                for lo in range(0, len(docs), 4096):
                    hi = min(lo + 4096, len(docs))
                    cut = offsets[lo: hi + 1].tolist()
                    own = [ids[a:b].astype("<u4") for a, b in zip(cut, cut[1:], strict=False)]
                    key = np.array(docs[lo:hi])
                    columns = [
                        pa.array(key, mask=key == NULL_DOC), pa.array(np.array(cut[:-1]) + base), pa.array(np.diff(cut)),
                        pa.array([zlib.crc32(x.tobytes()) for x in own], pa.int64()),
                    ]
                    extra = [pa.array([x.astype(np.int64) for x in own], pa.list_(pa.int64()))] if with_ids else []
                    yield pa.RecordBatch.from_arrays([*columns, *extra], ["doc_id", "start", "n_tokens", "ids_crc32", *["ids"] * with_ids])

    table = spark.createDataFrame(shards or [("", 0, 2)], "name string, base long, width int")
    table = table.filter("name <> ''").repartition(max(1, len(shards)))
    return map_arrow(table, run, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<bigint>" * with_ids)
