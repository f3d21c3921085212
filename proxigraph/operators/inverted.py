"""Inverted-file baseline: k-means cells, lists of members, search of the nearest cells."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.distance import nearest_rows
from proxigraph.functions.prng import draw
from proxigraph.operators import resident
from proxigraph.operators.exact import exact_knn, nearest_of, top_k
from proxigraph.operators.index import SearchResult
from proxigraph.operators.model import PointSet, to_lists, to_matrix
from proxigraph.runtime import map_arrow, settle

#: Centroids are sent to all executors up to this size.
CENTROID_BYTES = 64 << 20
#: Members of a list that one task scans as a unit.
LIST_ROWS = 65_536
#: Rows that `assign` hands on at once.
ASSIGNED_ROWS = 2048
SCALE = 1 << 20


def first_centroids(points: PointSet, cells: int, seed: int = 42) -> DataFrame:
    """cell, centroid: the points with the least draws."""
    rows = points.plain().withColumn("h", draw(seed, "id")).orderBy("h", "id").limit(cells)
    return rows.select((F.row_number().over(Window.orderBy("h", "id")) - 1).alias("cell"), F.col("vec").alias("centroid"))


def _collected(cells: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """Names and centroids, or None if they are too large to send to all executors."""
    size = cells.agg(F.count("*").alias("n"), F.max(F.size("centroid")).alias("d")).first()
    if (size["n"] or 0) * (size["d"] or 0) * 8 > CENTROID_BYTES:
        return None
    rows = cells.orderBy("cell").toArrow()
    return rows.column("cell").to_numpy().astype(np.int64), to_matrix(rows.column("centroid"))


def assign(points: PointSet, cells: DataFrame, closest: int = 1) -> DataFrame:
    """id, vec, cell, dist: each point's `closest` cells by (distance, cell). Few centroids are sent to all
    executors after their size is checked; more are searched as points are, block by block."""
    spark = points.df.sparkSession
    known = _collected(cells)
    metric = points.metric
    if known is None:
        centers = PointSet(cells.select(F.col("cell").cast("long").alias("id"), F.col("centroid").alias("vec")), metric=metric)
        near = exact_knn(centers, points, closest).select("qid", F.col("id").cast("int").alias("cell"), "dist")
        return points.plain().join(near, F.col("id") == F.col("qid")).select("id", "vec", "cell", "dist")
    shared = spark.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, centers = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            step = max(1, ASSIGNED_ROWS // min(closest, len(centers)))  # every row leaves with its vector
            for lo in range(0, b.num_rows, step):
                part = b.slice(lo, step)
                x = to_matrix(part.column(1))
                near, d = nearest_rows(x, centers, closest, metric)
                who = np.repeat(np.arange(len(x)), near.shape[1])
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).take(pa.array(who)), to_lists(x[who]), pa.array(names[near.reshape(-1)].astype(np.int32)), pa.array(d.reshape(-1))], ["id", "vec", "cell", "dist"],
                )

    return map_arrow(points.plain(), run, "id long, vec array<double>, cell int, dist double")


def kmeans_step(points: PointSet, cells: DataFrame) -> DataFrame:
    """cell, centroid after one step; means are summed in fixed point, an empty cell stays. A task sends
    one row of sums per cell and slice of points, whatever the number of points."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell, x = b.column(1).to_numpy(zero_copy_only=False), to_matrix(b.column(0)) * SCALE
                fixed = np.copysign(np.floor(np.abs(x) + 0.5), x).astype(np.int64)  # halves go away from zero, as SQL rounds
                names, back = np.unique(cell, return_inverse=True)
                sums = np.zeros((len(names), x.shape[1]), dtype=np.int64)
                np.add.at(sums, back, fixed)
                yield pa.RecordBatch.from_arrays([pa.array(names), to_lists(sums, pa.int64()), pa.array(np.bincount(back))], ["cell", "sums", "n"])

    part = map_arrow(assign(points, cells).select("vec", "cell"), run, "cell int, sums array<bigint>, n long")
    sums = part.select("cell", F.posexplode("sums").alias("j", "x"), "n").groupBy("cell", "j").agg(F.sum(F.col("x").cast("decimal(38,0)")).alias("s"), F.sum("n").alias("n"))
    mean = sums.select("cell", "j", (F.col("s").cast("double") / SCALE / F.col("n")).alias("x"))
    mean = mean.groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("m")).select("cell", F.transform("m", lambda s: s["x"]).alias("new"))
    return cells.join(mean, "cell", "left").select("cell", F.coalesce("new", "centroid").alias("centroid"))


def train_cells(points: PointSet, cells: int, iters: int = 10, seed: int = 42) -> DataFrame:
    out = settle(first_centroids(points, cells, seed), "cells")
    for _ in range(iters):
        out = settle(kmeans_step(points, out), "cells")
    return out


@dataclass(frozen=True)
class InvertedIndex:
    """postings: cell (of the store), list, id, vec; a list of more than LIST_ROWS members owns several
    cells, first[list] to first[list + 1] - 1, dealt by hashed id."""

    cells: DataFrame
    postings: DataFrame
    folder: str
    lists: int
    first: np.ndarray
    metric: str

    @classmethod
    def build(cls, points: PointSet, cells: int, iters: int = 10, seed: int = 42, closure: int = 1, train_on: PointSet | None = None) -> InvertedIndex:
        """closure: in how many nearest lists a point is put; train_on: other points to train with."""
        trained = train_cells(train_on or points, cells, iters, seed)
        members = settle(assign(points, trained, closure).select(F.col("cell").alias("list"), "id", "vec"), "members")
        counts = {r["list"]: r["count"] for r in members.groupBy("list").count().collect()}  # one row a list
        lists = max([*counts, cells - 1]) + 1
        blocks = np.array([max(1, -(-counts.get(c, 0) // LIST_ROWS)) for c in range(lists)], dtype=np.int64)
        first = np.concatenate([[0], np.cumsum(blocks)])
        shared = points.df.sparkSession.sparkContext.broadcast(first)

        def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            begin = shared.value
            for b in batches:
                if b.num_rows:
                    own = b.column(0).to_numpy(zero_copy_only=False)
                    cell = begin[own] + b.column(3).to_numpy(zero_copy_only=False) % np.diff(begin)[own]
                    yield pa.RecordBatch.from_arrays([pa.array(cell), b.column(0), b.column(1), b.column(2)], ["cell", "list", "id", "vec"])

        salted = members.select("list", "id", "vec", F.pmod(F.xxhash64("id"), F.lit(1 << 30)).alias("salt"))
        dealt = map_arrow(salted, place, "cell long, list int, id long, vec array<double>").repartition("cell").sortWithinPartitions("cell", "id")
        return cls(trained, *resident.store(dealt, "postings"), lists, first, points.metric)

    def probed(self, queries: PointSet, probe: int, coarse=None, width: int | None = None) -> DataFrame:
        """qid, qvec, cell: the lists each query visits, found over all centroids or by a graph on them."""
        if coarse is None:
            near = assign(queries, self.cells, probe)
            return near.select(F.col("id").alias("qid"), F.col("vec").alias("qvec"), "cell")
        found = coarse.search(queries, probe, width or max(probe, 16)).results
        return found.join(queries.plain().select(F.col("id").alias("qid"), F.col("vec").alias("qvec")), "qid").select("qid", "qvec", F.col("id").cast("int").alias("cell"))

    def routed(self, probed: DataFrame) -> DataFrame:
        """(cell, list, id, vec): every probed query for each cell of its lists."""
        spans = F.array(*[F.lit(int(x)) for x in self.first]) if len(self.first) <= 4096 else None
        q = probed.select(F.col("cell").alias("list"), F.col("qid").alias("id"), F.col("qvec").alias("vec"))
        if spans is None:
            table = self.cells.sparkSession.createDataFrame([(i, int(a), int(b) - 1) for i, (a, b) in enumerate(zip(self.first, self.first[1:], strict=False))], "list int, a long, b long")
            return q.join(table, "list").select(F.explode(F.sequence("a", "b")).alias("cell"), "list", "id", "vec")
        last = F.element_at(spans, F.col("list") + 2) - 1
        return q.select(F.explode(F.sequence(F.element_at(spans, F.col("list") + 1), last)).alias("cell"), "list", "id", "vec").withColumn("cell", F.col("cell").cast("long"))

    def coarse_graph(self, **params):
        """A layered graph over the centroids, to find the cells of a query."""
        from proxigraph.operators.index import layered_graph

        return layered_graph(PointSet(self.cells.select(F.col("cell").cast("long").alias("id"), F.col("centroid").alias("vec")), metric=self.metric), **params)

    def _met(self, probed: DataFrame, k: int | None, radius: float | None) -> DataFrame:
        """qid, ids, dists, met: of each query and cell, the k nearest members or those within radius, and
        how many members were compared. A task holds one cell, and keeps k answers a query of it."""
        metric = self.metric

        def load(table: pa.Table):
            return table.column("id").to_numpy(), to_matrix(table.column("vec"))

        def ask(held, table: pa.Table) -> pa.RecordBatch:
            ids, x = held
            q_ids, q = table.column("id").to_numpy(), to_matrix(table.column("vec"))
            r, i, d = nearest_of(q_ids, q, ids, x, metric, k, radius)
            order = np.lexsort((i, d, r))
            r, i, d = r[order], i[order], d[order]
            offsets = pa.array(np.concatenate([[0], np.cumsum(np.bincount(r, minlength=len(q)))]).astype(np.int32))
            return pa.RecordBatch.from_arrays(
                [pa.array(q_ids), pa.ListArray.from_arrays(offsets, pa.array(i)), pa.ListArray.from_arrays(offsets, pa.array(d)), pa.array(np.full(len(q), len(x)))],
                ["qid", "ids", "dists", "met"],
            )

        return resident.answer(self.routed(probed), self.postings, self.folder, ["id", "vec"], int(self.first[-1]), load, ask, "qid long, ids array<bigint>, dists array<double>, met long")

    def search(self, queries: PointSet, k: int = 10, probe: int = 1, coarse=None) -> SearchResult:
        """The k nearest among the members of the `probe` nearest cells. The stats count one distance
        per centroid and per list entry met."""
        probed = self.probed(queries, probe, coarse)
        met = settle(self._met(probed, k, None), "candidates")
        n = self.lists if coarse is None else 0
        stats = met.groupBy("qid").agg(F.sum("met").alias("met"))
        ids = queries.plain().select(F.col("id").alias("qid"))
        stats = ids.join(stats, "qid", "left").select("qid", F.lit(probe).cast("long").alias("hops"), (F.coalesce("met", F.lit(0)) + n).alias("dist_comps"), F.coalesce("met", F.lit(0)).cast("long").alias("visited"))
        return SearchResult(top_k(_pairs(met).dropDuplicates(["qid", "id"]), k), stats)

    def range_search(self, queries: PointSet, radius: float, probe: int = 1) -> DataFrame:
        return _pairs(self._met(self.probed(queries, probe), None, radius)).dropDuplicates(["qid", "id"])


def _pairs(met: DataFrame) -> DataFrame:
    return met.select("qid", F.explode(F.arrays_zip("ids", "dists")).alias("e")).select("qid", F.col("e.ids").alias("id"), F.col("e.dists").alias("dist"))
