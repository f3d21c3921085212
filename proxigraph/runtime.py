"""Session helpers: the shared folder of the cluster and tables settled in it."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType, _parse_datatype_string

_LOCAL_DIRS: dict[str, str] = {}
_SHIPPED: set[str] = set()
#: Of a worker: the kernel that it ran last, and what that kernel keeps from task to task.
_KERNEL: list[str] = [""]
_KEPT: dict[str, object] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir).

    Only a local master may go without that setting: there the driver's temp folder is also
    every executor's. On a cluster a missing setting is an error, never a machine-local folder.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder shared by driver and executors")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL_DIRS:
        _LOCAL_DIRS[app] = "file://" + tempfile.mkdtemp(prefix="proxigraph-")
    return _LOCAL_DIRS[app]


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that no other call gets."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


#: Rows that a kernel sees at once; Arrow's own batches hold ten times as many, whatever their size.
KERNEL_ROWS = 1024


@contextmanager
def _frugal(spark: SparkSession) -> Iterator[None]:
    """What runs inside leaves no shuffle files behind once it has ended, and hands Python batches of
    KERNEL_ROWS rows at most."""
    wanted = {
        "spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true",
        "spark.sql.execution.arrow.maxRecordsPerBatch": str(KERNEL_ROWS),
    }
    before = {key: spark.conf.get(key, None) for key in wanted}
    try:
        for key, value in wanted.items():
            spark.conf.set(key, value)
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def settle(df: DataFrame, name: str, spent: list[str] | None = None) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back.

    Cuts the lineage of loops and keeps costly steps from running twice; survives lost
    executors, as the files are not theirs. The path is added to `spent`, if given, for discard.
    Shuffle files of the write go with it, rather than when the driver next collects garbage.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    with _frugal(spark):
        df.write.parquet(path)
    if spent is not None:
        spent.append(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, spent: list[str]) -> None:
    """Delete settled tables that nothing reads any more."""
    jvm = spark._jvm
    for path in spent:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
    spent.clear()


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Make this package importable in the executors' Python, once per application."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    here = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="proxigraph-"), "proxigraph.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as out:
        for folder, _, names in os.walk(here):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    out.write(full, os.path.join("proxigraph", os.path.relpath(full, here)))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def _give_back() -> None:
    """Return what a finished task has freed to the system: workers are used again for other stages."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def kept(key: str, make: Callable[[], object]):
    """What make() gives, held by this worker for later tasks of the kernel that asks; it is freed when
    the worker turns to another kernel, as workers serve all stages of an application."""
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def _turn_to(kernel: str) -> None:
    if _KERNEL[0] != kernel:
        _KERNEL[0] = kernel
        _KEPT.clear()


def map_arrow(df: DataFrame, function, schema, rows: int = KERNEL_ROWS) -> DataFrame:
    """df.mapInArrow(function, schema) with this package at hand in the workers. Batches are cut into
    slices of `rows` rows, so that what a kernel copies out of a batch of long texts stays small;
    empty batches are left out. Whoever runs the result, this session hands Python KERNEL_ROWS rows at
    once from here on (fewer, if it was set so): batches of 10,000 long texts, Spark's default, stand
    in the memory of the executor and of Python, in and out."""
    spark, name = df.sparkSession, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= KERNEL_ROWS:
        spark.conf.set(name, str(KERNEL_ROWS))
    kernel = f"{function.__module__}.{function.__qualname__}"

    def sliced(batches):
        _turn_to(kernel)
        yield from function(b.slice(at, rows) for b in batches for at in range(0, b.num_rows, rows))
        _give_back()

    ship(df.sparkSession)
    return df.mapInArrow(sliced, schema)


def with_fields(df: DataFrame, fields: str) -> StructType:
    """The schema of df with the fields of a DDL string behind, whatever df's columns are called."""
    return StructType(df.schema.fields + _parse_datatype_string(fields).fields)


def broadcast_if_small(df: DataFrame, most_rows: int = 100_000) -> DataFrame:
    """df with a broadcast hint if it has at most most_rows rows, else as it is. df should be settled,
    as it is counted; its rows should be narrow."""
    return F.broadcast(df) if df.count() <= most_rows else df
