"""Vector tables in the formats Spark reads, edge exports, and the append-only table of runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.operators.model import PointSet


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet", id: str = "id", vec: str = "vec", metric: str = "l2", sep: str = " ") -> PointSet:
    """A point set from Parquet, ORC, JSON or CSV. In CSV the vector is one column of numbers
    separated by `sep`. Only the two columns are read."""
    reader = spark.read.option("header", "true") if fmt == "csv" else spark.read
    t = reader.format(fmt).load(path)
    v = F.col(vec)
    if fmt == "csv":
        v = F.transform(F.split(v, sep), lambda x: x.cast("double"))
    return PointSet(t.select(F.col(id).cast("long").alias("id"), v.cast("array<double>").alias("vec")), metric=metric)


def write_vectors(points: PointSet, path: str, fmt: str = "parquet", sep: str = " ") -> None:
    t = points.plain()
    if fmt == "csv":
        t = t.select("id", F.array_join(F.transform("vec", lambda x: x.cast("string")), sep).alias("vec"))
    writer = t.write.mode("overwrite")
    (writer.option("header", "true") if fmt == "csv" else writer).format(fmt).save(path)


def export_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = edges.select("src", "dst", "dist").write.mode("overwrite")
    (writer.option("header", "true") if fmt == "csv" else writer).format(fmt).save(path)


def append_runs(runs: DataFrame, path: str) -> None:
    """Add measured runs to their table; params are kept as JSON."""
    runs.withColumn("params", F.to_json("params")).write.mode("append").parquet(path)


def read_runs(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).withColumn("params", F.from_json("params", "map<string,string>"))
