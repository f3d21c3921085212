"""Raw vector files: a count and a dimension (unsigned 32-bit), then rows of u8, i8 or f32 components.

A Python data source reads and writes them; a file is read in ranges of rows, one task each.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from proxigraph.runtime import ship

TYPES = {"u8": ("<u1", "smallint"), "i8": ("<i1", "tinyint"), "f32": ("<f4", "float")}
ROWS_PER_TASK = 1 << 18


def _open(path: str):
    from pyarrow import fs

    if path.startswith("file:"):
        return fs.LocalFileSystem(), "/" + path[5:].lstrip("/")
    return (fs.LocalFileSystem(), path) if "://" not in path else fs.FileSystem.from_uri(path)


class Rows(InputPartition):
    def __init__(self, first: int, count: int, dims: int):
        self.first, self.count, self.dims = first, count, dims


class RawReader(DataSourceReader):
    def __init__(self, path: str, kind: str, rows_per_task: int):
        self.path, self.kind, self.rows_per_task = path, kind, rows_per_task

    def partitions(self):
        system, path = _open(self.path)
        with system.open_input_file(path) as f:
            n, d = struct.unpack("<II", f.read(8))
        return [Rows(a, min(self.rows_per_task, n - a), d) for a in range(0, n, self.rows_per_task)] or [Rows(0, 0, d)]

    def read(self, partition):
        dtype, _ = TYPES[self.kind]
        dtype = np.dtype(dtype)
        system, path = _open(self.path)
        width = partition.dims * dtype.itemsize
        with system.open_input_file(path) as f:
            for a in range(0, partition.count, 65_536):
                m = min(65_536, partition.count - a)
                f.seek(8 + (partition.first + a) * width)
                x = np.frombuffer(f.read(m * width), dtype=dtype).reshape(m, partition.dims)
                wide = {"u8": np.int16, "i8": np.int8, "f32": np.float32}[self.kind]
                offsets = pa.array(np.arange(m + 1, dtype=np.int32) * partition.dims)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.arange(m, dtype=np.int64) + partition.first + a), pa.ListArray.from_arrays(offsets, pa.array(x.astype(wide).reshape(-1)))], ["id", "vec"])


class RawVectors(DataSource):
    @classmethod
    def name(cls):
        return "rawvec"

    def schema(self):
        return f"id bigint, vec array<{TYPES[self.options.get('kind', 'f32')][1]}>"

    def reader(self, schema):
        return RawReader(self.options["path"], self.options.get("kind", "f32"), int(self.options.get("rowspertask", ROWS_PER_TASK)))


def read_raw(spark: SparkSession, path: str, kind: str = "f32", rows_per_task: int = ROWS_PER_TASK) -> DataFrame:
    """id (the row's place), vec of a raw file."""
    ship(spark)
    spark.dataSource.register(RawVectors)
    return spark.read.format("rawvec").option("path", path).option("kind", kind).option("rowspertask", str(rows_per_task)).load()


def write_raw(vectors: DataFrame, path: str, kind: str = "f32") -> int:
    """Write vec in ascending id order to one raw file, streamed through the driver row range by row
    range; returns the count. Meant for exchange of moderate files; indexes are saved as Parquet."""
    dtype = np.dtype(TYPES[kind][0])
    system, name = _open(path)
    n = vectors.count()
    first = vectors.select(F.size("vec").alias("d")).first()
    d = first["d"] if first else 0
    with system.open_output_stream(name) as out:
        out.write(struct.pack("<II", n, d))
        for row in vectors.orderBy("id").select("vec").toLocalIterator():
            out.write(np.array(row["vec"]).astype(dtype).tobytes())
    return n
