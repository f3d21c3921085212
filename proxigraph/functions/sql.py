"""The SQL surface: vector functions, a top-k aggregate, and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

from proxigraph.operators.kernels import schedule
from proxigraph.runtime import ship

_FOLD = "aggregate({terms}, 0D, (acc, x) -> acc + x)"
#: SQL bodies, which Spark puts in place of the call, so that they are optimised with the query.
FUNCTIONS = {
    "vec_l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "sqrt(" + _FOLD.format(terms="zip_with(a, b, (x, y) -> (x - y) * (x - y))") + ")"),
    "vec_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", _FOLD.format(terms="zip_with(a, b, (x, y) -> x * y)")),
    "vec_norm": ("a ARRAY<DOUBLE>", "DOUBLE", "sqrt(" + _FOLD.format(terms="transform(a, x -> x * x)") + ")"),
}


@F.pandas_udf(DoubleType())
def vec_l2_batch(a: pd.Series, b: pd.Series) -> pd.Series:
    """l2 of wide vectors, a batch at a time, with the bits of the SQL fold."""
    if not len(a):
        return pd.Series([], dtype=float)
    x, y = np.stack(a.to_numpy()).T, np.stack(b.to_numpy()).T
    acc = np.zeros(x.shape[1])
    for p, q in zip(x, y, strict=True):
        acc += (p - q) * (p - q)
    return pd.Series(np.sqrt(acc))


@F.pandas_udf(ArrayType(LongType()))
def topk_merge(dist: pd.Series, id: pd.Series, k: pd.Series) -> list:
    """Aggregate: the ids of the k smallest (dist, id) of a group."""
    if not len(dist):
        return []
    order = np.lexsort((id.to_numpy(), dist.to_numpy()))[: int(k.iloc[0])]
    return id.to_numpy()[order].tolist()


class PrefixSchedule:
    """Table function prefix_schedule(n, cap): the batches of a build."""

    def eval(self, n: int, cap: int):
        for i, (lo, hi) in enumerate(schedule(n, cap)):
            yield i, lo, hi, hi - lo + 1


class AnnSearch:
    """Table function ann_search(query, path, k, width): nearest ids of one query in a saved version of an
    index, by its own metric. A worker opens the shards one after the other and holds one at a time
    (the last one stays for the next query), so its memory does not grow with the index."""

    def __init__(self):
        self.manifests: dict[str, tuple] = {}
        self.last: tuple[tuple[str, int], object] | None = None

    def _manifest(self, path: str):
        if path not in self.manifests:
            import json

            from pyarrow import fs

            from proxigraph.operators.resident import filesystem

            system, root = filesystem(path)
            found = [f.path for f in system.get_file_info(fs.FileSelector(f"{root}/manifest")) if f.path.endswith(".json")]
            with system.open_input_file(found[0]) as f:
                manifest = json.loads(json.loads(f.read().decode().splitlines()[0])["manifest"])
            cells = sorted(int(f.base_name[5:]) for f in system.get_file_info(fs.FileSelector(f"{root}/rows")) if f.base_name.startswith("cell="))
            self.manifests[path] = (manifest["metric"], cells)
        return self.manifests[path]

    def _shard(self, path: str, cell: int, metric: str):
        from proxigraph.operators.index import LOADED, _load
        from proxigraph.operators.resident import open_cell

        if self.last is None or self.last[0] != (path, cell):
            self.last = ((path, cell), _load(open_cell(f"{path}/rows", cell, LOADED), metric))
        return self.last[1]

    def eval(self, query: list, path: str, k: int, width: int):
        from proxigraph.operators import kernels as K

        found = []
        q = np.array(query, dtype=float)[:, None]
        metric, cells = self._manifest(path)
        for cell in cells:
            shard = self._shard(path, cell, metric)
            hits = K.layered_search(shard.graph, q, width, k) if shard.graph.upper else K.beam_search(shard.graph, q, width, k)
            at, d = hits.nearest(k)
            _, ids, far = shard.expand(at, d, (at >= 0) & np.isfinite(d), k)
            found += list(zip(far.tolist(), ids.tolist(), strict=True))
        for rank, (x, p) in enumerate(sorted(found)[:k], 1):
            yield rank, p, x


def register(spark: SparkSession) -> None:
    """Make the functions of this module callable from SQL in this session."""
    ship(spark)
    for name, (args, returns, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {returns} RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN if(vec_norm(a) * vec_norm(b) > 0, 1D - vec_dot(a, b) / (vec_norm(a) * vec_norm(b)), NULL)")
    spark.udf.register("vec_l2_batch", vec_l2_batch)
    spark.udf.register("topk_merge", topk_merge)
    batches = StructType([StructField("batch", LongType()), StructField("lo", LongType()), StructField("hi", LongType()), StructField("size", LongType())])
    hits = StructType([StructField("rank", LongType()), StructField("id", LongType()), StructField("dist", DoubleType())])
    spark.udtf.register("prefix_schedule", F.udtf(PrefixSchedule, returnType=batches))
    spark.udtf.register("ann_search", F.udtf(AnnSearch, returnType=hits))
