"""The batch-parallel build of one graph: every batch is the work of many tasks.

Step one of a batch deals its points to tasks; each searches the snapshot that the last batch left and
prunes what it visited. Step two groups the reversed edges by the vertex they reach, one hash exchange
without a total order, and each task merges and prunes the lists of its vertices. What a batch changes
is a table in the shared folder; the snapshot is the vectors and these tables in their order. A worker
keeps its snapshot and reads on from the last table it has seen, so a batch moves only its own edges,
and a worker that starts anew, after a lost executor, reads all of them and gets the same snapshot.

The first batches, too small to share, are built in one task. The edges are those of the kernel.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.operators import kernels as K
from proxigraph.operators import resident
from proxigraph.operators.model import PointSet, to_lists, to_matrix
from proxigraph.runtime import fresh_path, map_arrow, settle

LISTS = "pos long, nbrs array<bigint>, dists array<double>"
#: Batches up to this position are built in one task.
SMALL = 2048
#: Points that a task of step one has at least.
LEAST_POINTS = 16


@dataclass(frozen=True)
class Plan:
    """What all workers need to know of a build."""

    vectors: str
    metric: str
    degree: int
    width: int
    alpha: float
    seed: int


class Snapshot:
    """A worker's graph, and how many tables of changes it has taken in."""

    def __init__(self, plan: Plan):
        table = _read(plan.vectors, ["id", "vec"])
        order = np.argsort(table.column("id").to_numpy(), kind="stable")
        table = table.take(pa.array(order)).combine_chunks()
        self.ids = table.column("id").to_numpy()
        vecs = to_matrix(table.column("vec")).T
        self.graph = K.empty_graph(vecs, plan.degree, K.medoid(vecs, plan.metric), plan.metric)
        place = K.hashed_order(self.ids, plan.seed)
        self.order = place[place != self.graph.start]
        self.seen = 0

    def upto(self, changes: list[str]) -> Snapshot:
        for path in changes[self.seen:]:
            t = _read(path, ["pos", "nbrs", "dists"])
            if t.num_rows:
                pos = t.column("pos").to_numpy()
                self.graph.nbrs[pos] = to_matrix(t.column("nbrs")).astype(np.int64)
                self.graph.dists[pos] = to_matrix(t.column("dists"))
        self.seen = len(changes)
        return self


_HELD: dict[Plan, Snapshot] = {}


def _read(path: str, columns: list[str]) -> pa.Table:
    import pyarrow.parquet as pq
    from pyarrow import fs

    system, root = resident.filesystem(path)
    names = sorted(f.path for f in system.get_file_info(fs.FileSelector(root)) if f.path.endswith(".parquet"))
    return pa.concat_tables([pq.read_table(n, filesystem=system, columns=columns) for n in names]).combine_chunks()


def snapshot(plan: Plan, changes: list[str]) -> Snapshot:
    """The worker's snapshot after these changes; another build's, or one that is ahead, is let go."""
    held = _HELD.get(plan)
    if held is None or held.seen > len(changes):
        _HELD.clear()
        held = _HELD[plan] = Snapshot(plan)
    return held.upto(changes)


def _lists(pos: np.ndarray, nbrs: np.ndarray, dists: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(pos), to_lists(nbrs, pa.int64()), to_lists(dists)], ["pos", "nbrs", "dists"])


def _write(df: DataFrame, name: str) -> str:
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return path


def build(points: PointSet, degree: int = 64, width: int = 128, alpha: float = 1.2, theta: float = 0.02, rule: str = "inclusive", seed: int = 42, tasks: int | None = None, joined: bool = True) -> tuple[DataFrame, int, int]:
    """Rows (see index.ROWS, one cell) of the alpha graph over all points, the number of its batches and
    of distances computed. tasks: how many share a batch (None: as many as there are cores).

    Every worker holds the vectors and lists of the whole graph; more points than a worker has room for
    are built in shards.
    """
    from proxigraph.operators.index import ROWS, _unload

    spark = points.df.sparkSession
    tasks = tasks or spark.sparkContext.defaultParallelism
    plain = settle(points.plain(), "batch-points")
    reps = plain.groupBy("vec").agg(F.min("id").alias("id"))
    vectors = _write(reps.select("id", "vec"), "batch-vectors")
    if not resident.openable(vectors):
        raise ValueError("this engine needs a shared folder that tasks can open")
    plan = Plan(vectors, points.metric, degree, width, alpha, seed)
    n = spark.read.parquet(vectors).count()
    batches = K.schedule(max(0, n - 1), max(1, math.ceil(theta * n)), rule)
    together = [b for b in batches if b[1] <= SMALL]
    changes: list[str] = []
    spent = spark.sparkContext.accumulator(0)

    def begin(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts:
            if part.num_rows:
                own = Snapshot(plan)
                for lo, hi in together:
                    spent.add(K.insert_batch(own.graph, own.order[lo - 1: hi], degree, width, alpha))
                used = np.flatnonzero((own.graph.nbrs >= 0).any(axis=1))
                yield _lists(used, own.graph.nbrs[used], own.graph.dists[used])

    if together:
        changes.append(_write(map_arrow(spark.range(1).coalesce(1), begin, LISTS), "batch-changes"))

    for lo, hi in batches[len(together):]:
        known = list(changes)
        share = max(1, min(tasks, -(-(hi - lo + 1) // LEAST_POINTS)))

        def forward(parts: Iterator[pa.RecordBatch], known=known) -> Iterator[pa.RecordBatch]:
            for part in parts:
                if part.num_rows:
                    own = snapshot(plan, known)
                    batch = own.order[part.column(0).to_numpy() - 1]
                    out, far, comps = K.searched(own.graph, batch, degree, width, alpha)
                    spent.add(comps)
                    yield _lists(batch, out, far)

        def backward(parts: Iterator[pa.RecordBatch], known=known) -> Iterator[pa.RecordBatch]:
            held = [p for p in parts if p.num_rows]
            if held:
                own = snapshot(plan, known)
                target, source, dist = (np.concatenate([p.column(i).to_numpy() for p in held]) for i in range(3))
                used, nbrs, dists = K.merged_arrivals(own.graph, source, target, dist, degree, alpha)
                yield _lists(used, nbrs, dists)

        new = _write(map_arrow(spark.range(lo, hi + 1, 1, share), forward, LISTS), "batch-changes")
        changes.append(new)
        edges = spark.read.parquet(new).select("pos", F.explode(F.arrays_zip("nbrs", "dists")).alias("e")).filter("e.nbrs >= 0")
        dealt = edges.select(F.col("e.nbrs").alias("target"), F.col("pos").alias("source"), F.col("e.dists").alias("dist")).repartition(share, "target")
        changes.append(_write(map_arrow(dealt, backward, LISTS), "batch-changes"))

    def end(table: pa.Table) -> pa.Table:
        own = Snapshot(plan).upto(changes)
        if joined:
            K.connect(own.graph)
        members = table.sort_by("id")
        of = np.searchsorted(own.ids, members.column("rep").to_numpy())
        return _unload(own.graph, own.ids, 0, 0, len(batches), members.column("id").to_numpy(), of)

    named = plain.join(reps.select(F.col("id").alias("rep"), "vec"), "vec").select(F.lit(0).alias("g"), "id", "rep")
    return named.groupBy("g").applyInArrow(end, ROWS).drop("g"), len(batches), spent
