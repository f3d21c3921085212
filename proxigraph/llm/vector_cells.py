"""What the two vector searches share: clean vectors, a bounded sample, and cells of rows and queries."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.runtime import map_arrow, settle

#: Rows of the sample from which indexes are fitted and first thresholds are taken, at most about.
SAMPLE_ROWS = 8192
#: Queries that meet in one cell, at most about; beyond, the rows of a cell are dealt out again.
CELL_QUERIES = 32_768
CELL = "cell long, kind int, id long, data binary"


def clean_vectors(rows: DataFrame, id_col: str, vec_col: str, change: Callable[[np.ndarray], np.ndarray] | None = None, keep_zero: bool = False) -> DataFrame:
    """(id, data): the components of every usable vector as little-endian doubles.

    Left out: null ids; null vectors; vectors with a null or non-finite component; zero vectors, unless
    keep_zero; vectors of another length than the most common one (the shorter of two as common). Of
    several rows with one id the one with the least bytes stays.
    """
    sizes = rows.filter(F.col(vec_col).isNotNull()).groupBy(F.size(vec_col).alias("d")).count().orderBy(F.desc("count"), "d").first()
    d = sizes["d"] if sizes else 0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, data = [], []
            for key, v in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if key is None or not v.is_valid or len(v) != d or not d or v.values.null_count:
                    continue
                x = v.values.to_numpy(zero_copy_only=False).astype(np.float64)
                if np.isfinite(x).all() and (keep_zero or x.any()):
                    ids.append(key)
                    data.append((change(x) if change else x).astype("<f8").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(data, pa.binary())], ["id", "data"])

    found = map_arrow(rows.select(F.col(id_col).cast("long").alias("id"), vec_col), run, "id long, data binary")
    return found.groupBy("id").agg(F.min("data").alias("data"))


def matrix(column: pa.Array | list[bytes]) -> np.ndarray:
    values = column.to_pylist() if isinstance(column, pa.Array | pa.ChunkedArray) else column
    return np.frombuffer(b"".join(values), dtype="<f8").reshape(len(values), -1)


@dataclass
class Sample:
    ids: np.ndarray
    rows: np.ndarray
    count: int  # of the whole table
    longest: float  # largest squared norm of the whole table


def sample(vectors: DataFrame, most: int = SAMPLE_ROWS) -> Sample:
    """A sample by hashed id of about `most` rows, with the size and largest squared norm of all."""

    def norms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_pydict({"n": [batch.num_rows], "m": [float((matrix(batch.column(0)) ** 2).sum(axis=1).max())]})

    row = map_arrow(vectors.select("data"), norms, "n long, m double").agg(F.sum("n").alias("n"), F.max("m").alias("m")).first()
    n = row["n"] or 0
    bound = int(min(1.0, most / max(1, n)) * 0xFFFFFFFF)
    chosen = vectors.filter(F.xxhash64("id").bitwiseAND(0xFFFFFFFF) <= bound).toPandas().sort_values("id")
    data = matrix([bytes(x) for x in chosen["data"]]) if len(chosen) else np.empty((0, 0))
    return Sample(chosen["id"].to_numpy(np.int64), data, n, row["m"] or 0.0)


def least_scores(queries: np.ndarray, ids: np.ndarray, known: Sample, k: int) -> np.ndarray:
    """For each query a score that its k-th best candidate reaches at least, from the sample."""
    if len(known.ids) <= k:
        return np.full(len(queries), -np.inf)
    scores = queries @ known.rows.T
    own = np.searchsorted(known.ids, ids)
    own[own == len(known.ids)] = 0
    same = np.flatnonzero(known.ids[own] == ids)
    scores[same, own[same]] = -np.inf
    low = np.partition(scores, -k, axis=1)[:, -k]
    return low - np.abs(low) * 1e-9 - 1e-12


def deal_queries(n_queries: int) -> int:
    return max(1, -(-n_queries // CELL_QUERIES))


def in_cells(rows: DataFrame, queries: DataFrame, dealt: int, load: Callable, probe: Callable, schema: str) -> DataFrame:
    """Run every query of a cell against the rows of the cell.

    rows and queries have cell, id and data. The rows of a cell must be bounded: load(ids, datas)
    makes an index of them, then probe(index, ids, datas) -> RecordBatch is called for batches of
    queries, which are streamed. With dealt > 1, queries of a cell are split by hash into so many
    cells, each with a copy of the rows.
    """
    part = F.explode(F.sequence(F.lit(0), F.lit(dealt - 1)))
    left = rows.select("cell", F.lit(0).alias("kind"), "id", "data", part.alias("part"))
    right = queries.select("cell", F.lit(1).alias("kind"), "id", "data", F.pmod(F.xxhash64("id"), F.lit(dealt)).cast("int").alias("part"))
    both = left.unionByName(right).select((F.col("cell") * dealt + F.col("part")).alias("cell"), "kind", "id", "data")
    both = both.repartition("cell").sortWithinPartitions("cell", "kind")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, index, ids, datas = None, None, [], []
        for batch in batches:
            cell, kind = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            key = cell * 2 + kind
            cuts = [0, *(np.flatnonzero(np.diff(key)) + 1).tolist(), len(key)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if a == b:
                    continue
                if cell[a] != now:
                    now, index, ids, datas = cell[a], None, [], []
                own_ids, own = batch.column(2).slice(a, b - a).to_numpy(zero_copy_only=False), batch.column(3).slice(a, b - a).to_pylist()
                if kind[a] == 0:
                    ids.append(own_ids)
                    datas += own
                elif datas:
                    if index is None:
                        index = load(np.concatenate(ids), datas)
                    for lo in range(0, b - a, 1024):
                        yield probe(index, own_ids[lo: lo + 1024], own[lo: lo + 1024])

    return map_arrow(both, run, schema)


def best(found: DataFrame, k: int) -> DataFrame:
    """query_id, rank, vec_id, score: the k highest scores of each query, ties to the smaller vec_id."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def query_rows(vectors: DataFrame, every: int) -> DataFrame:
    return vectors.filter(F.col("id") % every == 0)


def spread(column: str, parts: Column | int) -> Column:
    return F.pmod(F.xxhash64(column, F.lit(7)), parts)


__all__ = ["CELL", "SAMPLE_ROWS", "Sample", "best", "clean_vectors", "deal_queries", "in_cells", "least_scores", "matrix", "query_rows", "sample", "settle", "spread"]
