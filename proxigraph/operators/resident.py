"""Cells that stay where they are: bounded groups of rows in folders of the shared store, which tasks open
when a query is routed to them. A search moves the queries and their answers, never the indexed rows.

Where the store is one that only Spark reads, the rows are shuffled to the queries instead.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.operators.exact import stream_cells
from proxigraph.runtime import fresh_path, map_arrow

#: Queries that one task answers from one cell, at most about; a cell may be opened by several tasks.
CELL_QUERIES = 32_768
#: Below this many queries a cell is not opened twice for the sake of idle cores.
LEAST_QUERIES = 64


def filesystem(uri: str):
    """(pyarrow file system, path) of a URI."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    if "://" not in uri:
        return fs.LocalFileSystem(), uri
    return fs.FileSystem.from_uri(uri)


def openable(path: str) -> bool:
    """Whether tasks can open the files under path themselves."""
    from pyarrow import fs

    try:
        system, root = filesystem(path)
        return system.get_file_info(root).type != fs.FileType.NotFound
    except (pa.ArrowException, OSError, ValueError):
        return False


def store(rows: DataFrame, name: str) -> tuple[DataFrame, str]:
    """Write rows (cell long, ...) with a folder per cell; returns them as read back, and the path. Rows
    should be grouped by cell already, else a cell has many small files."""
    spark = rows.sparkSession
    path = fresh_path(spark, name)
    rows.write.partitionBy("cell").parquet(path)
    return read(rows, path), path


def read(like: DataFrame, path: str) -> DataFrame:
    return like.sparkSession.read.schema(like.schema).parquet(path).select(*like.columns)


def open_cell(path: str, cell: int, columns: list[str]) -> pa.Table | None:
    """The rows of one cell, or None if it has none."""
    import pyarrow.parquet as pq
    from pyarrow import fs

    system, root = filesystem(path)
    names = [f.path for f in system.get_file_info(fs.FileSelector(f"{root}/cell={cell}", allow_not_found=True)) if f.path.endswith(".parquet")]
    parts = [pq.read_table(name, filesystem=system, columns=columns, partitioning=None) for name in sorted(names)]
    return pa.concat_tables(parts).combine_chunks() if parts else None


def _dealt(queries: DataFrame, cells: int) -> DataFrame:
    """Queries (cell, id, ...) by cell, those of a cell in as many parts as there are cores for, or as
    their number needs."""
    spark = queries.sparkSession
    n = queries.count()
    cores = spark.sparkContext.defaultParallelism
    each = -(-n // max(1, cells))
    parts = max(1, -(-each // CELL_QUERIES), min(-(-each // LEAST_QUERIES), -(-cores // max(1, cells))))
    tasks = min(cells * parts, max(cores, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    salted = queries.withColumn("_part", F.pmod(F.xxhash64("id", F.lit(3)), F.lit(parts)))
    return salted.repartition(max(1, tasks), "cell", "_part").drop("_part").sortWithinPartitions("cell")


def answer(queries: DataFrame, rows: DataFrame, path: str, columns: list[str], cells: int, load: Callable, ask: Callable, schema: str) -> DataFrame:
    """ask(load(rows of the cell), queries of the cell) -> RecordBatch, for all queries (cell, id, vec).
    Only one cell is held at a time."""
    queries = queries.select("cell", "id", "vec")
    if not openable(path):
        left = rows.select("cell", F.lit(0).alias("kind"), *columns)
        kinds = dict(rows.dtypes)
        none = [F.lit(None).cast(kinds[c]).alias(c) for c in columns if c not in ("id", "vec")]
        right = queries.select("cell", F.lit(1).alias("kind"), "id", F.col("vec").cast(kinds["vec"]).alias("vec"), *none).select("cell", "kind", *columns)
        both = left.unionByName(right).repartition("cell").sortWithinPartitions("cell", "kind")

        def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            last, held = None, None
            for _, table, whole in stream_cells(batches):
                if whole is not last:
                    last, held = whole, load(whole)
                yield ask(held, table)

        return map_arrow(both, meet, schema)

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            cell = batch.column(0).to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(cell)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if cell[a] != now:
                    now = cell[a]
                    table = open_cell(path, int(now), columns)
                    held = None if table is None else load(table)
                if held is not None:
                    yield ask(held, pa.Table.from_batches([batch.slice(a, b - a)]))

    return map_arrow(_dealt(queries, cells), visit, schema)
