"""Best-fit packing of documents into fixed-size sequences, large items matched first.

Documents longer than a sequence are cut; what is packed are pieces of 1 to `capacity` tokens. The
plan only needs how many pieces have each length: a table of at most `capacity` rows, however large
the corpus. On it the packer works with whole classes at once:

* pieces above a third of the capacity fit at most twice into a sequence: from the longest down,
  each class is matched with the longest other large class that still fits;
* the smaller pieces, longest first, go to the sequences with the smallest gap that holds them, as
  many to each as fit, before new sequences are opened.

A piece then finds its place from its rank among the pieces of its length, which is counted by
hashed slices, so that no length, however common, lands in one task.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, bisect_right, insort
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.llm import token_ids
from proxigraph.runtime import map_arrow, settle, with_fields

CAPACITY = 2048
END_ID = 0
SLICES = 1024
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


@dataclass
class Plan:
    """Segments: pieces of `length` with rank from `rank` on lie at `offset` of sequences `first`,
    first + 1, ... (one array entry each, sorted by length and rank)."""

    length: np.ndarray
    rank: np.ndarray
    first: np.ndarray
    offset: np.ndarray
    sequences: int


def plan(counts: dict[int, int], capacity: int) -> Plan:
    left = {s: n for s, n in counts.items() if n > 0}
    taken = dict.fromkeys(left, 0)
    segments: list[tuple[int, int, int, int]] = []
    by_gap: dict[int, list[tuple[int, int]]] = {}  # gap -> (first sequence, how many)
    gaps: list[int] = []
    opened = 0

    def leave(gap: int, first: int, n: int) -> None:
        if gap and n:
            if gap not in by_gap:
                by_gap[gap] = []
                insort(gaps, gap)
            by_gap[gap].append((first, n))

    def put(size: int, n: int, first: int, offset: int) -> None:
        segments.append((size, taken[size], first, offset))
        taken[size] += n
        left[size] -= n

    large = sorted(s for s in left if 3 * s > capacity)
    while large:
        a = large[-1]
        at = bisect_right(large, capacity - a)
        if at and large[at - 1] == a and left[a] == 1:
            at -= 1
        b = large[at - 1] if at else None
        n = left[a] if b is None else left[a] // 2 if b == a else min(left[a], left[b])
        put(a, n, opened, 0)
        if b is not None:
            put(b, n, opened, a)
        leave(capacity - a - (b or 0), opened, n)
        opened += n
        for s in {a, b} - {None}:
            if not left[s]:
                del large[bisect_left(large, s)]

    for s in sorted((s for s in left if 3 * s <= capacity), reverse=True):
        while left[s]:
            at = bisect_left(gaps, s)
            if at < len(gaps):
                gap = gaps[at]
                first, n = by_gap[gap].pop()
                if not by_gap[gap]:
                    del by_gap[gap], gaps[at]
            else:
                gap, first, n = capacity, opened, max(1, left[s] // (capacity // s))
                opened += n
            each = min(gap // s, left[s])
            used = min(n, left[s] // each)
            leave(gap, first + used, n - used)
            for k in range(each):
                put(s, used, first, capacity - gap + k * s)
            leave(gap - each * s, first, used)
    table = np.array(sorted(segments), dtype=np.int64).reshape(-1, 4)
    return Plan(*table.T, opened)


def pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str | None = None) -> DataFrame:
    """One row per piece of every document: its ids and then end_id, cut into pieces of `capacity`
    ids if longer, of which the first holds what is left over. A null or empty text is the end id."""
    path = vocabulary or token_ids.default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = token_ids.encoder(path)
        end = np.array([end_id], dtype="<u4").tobytes()
        for batch in batches:
            out: list[tuple] = []
            keys = batch.column(0).to_pylist()
            for lo, _, ids, lengths in encoder.encode(batch.column(1).to_pylist()):
                stops = np.cumsum(lengths)
                for k, (stop, size) in enumerate(zip(stops.tolist(), lengths.tolist(), strict=True)):
                    raw = ids[stop - size: stop].astype("<u4").tobytes() + end
                    begin, piece, stop = 0, 0, (size % capacity) + 1
                    while begin <= size:
                        out.append((keys[lo + k], piece, begin, stop - begin, zlib.crc32(raw[4 * begin: 4 * stop])))
                        begin, piece, stop = stop, piece + 1, stop + capacity
            columns = list(zip(*out, strict=True)) or [[]] * 5
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, PIECES)


def pack(found: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Rows of found, which has doc_id, piece and length (1 to capacity), plus sequence_id and offset.

    found must give the same rows each time it is read (a written table). Repeated rows are pieces
    of their own; columns of found with the new names are replaced. An empty table gives an empty result.
    """
    counts = {r["length"]: r["count"] for r in found.groupBy("length").count().collect()}  # at most `capacity` rows
    if any(not 1 <= s <= capacity for s in counts):
        raise ValueError(f"lengths must be 1 to {capacity}")
    made = found.sparkSession.sparkContext.broadcast(plan(counts, capacity))
    plain = found.drop("sequence_id", "offset")
    sliced = plain.withColumn("_pk_slice", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(SLICES)).cast("int"))
    bases = sliced.groupBy("length", "_pk_slice").agg(F.count("*").alias("_pk_n")).select(
        "length", "_pk_slice",
        (F.sum("_pk_n").over(Window.partitionBy("length").orderBy("_pk_slice")) - F.col("_pk_n")).alias("_pk_base"),
    )
    inside = F.row_number().over(Window.partitionBy("length", "_pk_slice").orderBy("doc_id", "piece"))
    ranked = sliced.withColumn("_pk_inside", inside).join(bases, ["length", "_pk_slice"])
    ranked = ranked.select(*plain.columns, (F.col("_pk_base") + F.col("_pk_inside") - 1).alias("_pk_rank"))
    place = (ranked.columns.index("length"), ranked.columns.index("_pk_rank"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = made.value
        wide = 1 << 50
        key = p.length * wide + p.rank  # Python's workers hold one small plan each
        for batch in batches:
            size, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in place)
            at = np.searchsorted(key, size * wide + rank, side="right") - 1
            columns = [batch.column(i) for i in range(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays(
                [*columns, pa.array(p.first[at] + rank - p.rank[at]), pa.array(p.offset[at])],
                [*batch.schema.names[:-1], "sequence_id", "offset"],
            )

    return map_arrow(ranked, run, with_fields(plain, "sequence_id long, offset long"))


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece of docs."""
    return pack(settle(pieces(docs, capacity, end_id, vocabulary), "pieces"), capacity)
