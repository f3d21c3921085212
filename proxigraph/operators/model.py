"""Point sets: the frames that every method takes, their checks and orders."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.prng import RANGE, draw

#: Parameters with a value of the reference's, or else of the open literature or our own.
DEFAULTS = {
    "k": 10, "degree": 64, "width": 128, "theta": 0.02, "most_eps": 0.25, "mst_near": 10, "mst_trees": 30, "undirect_cap": 2000,
    "alpha": 1.2, "mst_degree": 3, "leaf": 1000, "layer_degree": 16, "descent_trees": 10, "descent_leaf": 100, "descent_k": 40, "descent_delta": 0.001,
}
#: Points that one task builds and searches as a unit.
SHARD_ROWS = 100_000


@dataclass(frozen=True)
class PointSet:
    """A frame with an id and a vector column, and the metric its distances are taken in."""

    df: DataFrame
    id: str = "id"
    vec: str = "vec"
    metric: str = "l2"

    def plain(self) -> DataFrame:
        """(id, vec array<double>)."""
        return self.df.select(F.col(self.id).cast("long").alias("id"), F.col(self.vec).cast("array<double>").alias("vec"))

    def invalid(self) -> DataFrame:
        """(id, reason) of rows that cannot be indexed: null id or vector, null or non-finite
        component, a length other than the most common one, a repeated id."""
        p = self.plain()
        d = p.filter("vec is not null").groupBy(F.size("vec").alias("d")).count().orderBy(F.desc("count"), "d").first()
        d = d["d"] if d else 0
        bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
        reason = (
            F.when(F.col("id").isNull(), "null id").when(F.col("vec").isNull(), "null vector").when(F.size("vec") != d, "length")
            .when(bad, "component")
        )
        rows = p.select("id", reason.alias("reason")).filter("reason is not null")
        again = p.filter("id is not null").groupBy("id").count().filter("count > 1").select("id", F.lit("repeated id").alias("reason"))
        return rows.unionByName(again)

    def validate(self) -> PointSet:
        bad = self.invalid().limit(5).collect()
        if bad:
            raise ValueError(f"points that cannot be indexed: {[(r['id'], r['reason']) for r in bad]}")
        return self

    def ordered(self, seed: int = 42) -> DataFrame:
        """(id, vec, pos): positions 1..n in the order of (draw, id), counted range by range so that no
        task sees all rows."""
        p = self.plain().withColumn("h", draw(seed, "id"))
        slices = 1024
        p = p.withColumn("slice", F.floor(F.col("h") * slices / RANGE).cast("int"))
        base = p.groupBy("slice").count().select("slice", (F.sum("count").over(Window.orderBy("slice")) - F.col("count")).alias("base"))
        inside = F.row_number().over(Window.partitionBy("slice").orderBy("h", "id"))
        return p.withColumn("inside", inside).join(F.broadcast(base), "slice").select("id", "vec", (F.col("base") + F.col("inside")).alias("pos"))

    def sample(self, share: float, seed: int = 42) -> PointSet:
        return replace(self, df=self.df.filter(draw(seed, F.col(self.id)) < int(share * RANGE)))

    def split_queries(self, mod: int = 10) -> tuple[PointSet, PointSet]:
        """(base, queries): queries are the rows whose id is divisible by mod."""
        is_query = F.col(self.id) % mod == 0
        return replace(self, df=self.df.filter(~is_query)), replace(self, df=self.df.filter(is_query))


def to_matrix(column) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    if not n:
        return np.empty((0, 0))
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, -1)


def to_lists(x: np.ndarray, kind=None) -> pa.Array:
    """Rows of a matrix as a list column."""
    kind = kind or pa.float64()
    n, d = x.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * d), pa.array(np.ascontiguousarray(x).reshape(-1), kind))
