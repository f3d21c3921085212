"""Graph indexes: built shard by shard, searched by streaming queries through the shards.

Points are dealt to shards of bounded size, by cells of a coarse quantiser that is fitted on a bounded
sample, or by hashed id. A task builds one shard's graph by any of the methods, or, with engine
"batches", many tasks build it together; a point's row then holds its vector and its lists. Rows lie in
a folder per shard. A search deals the queries to the shards they are routed to, opens a shard's files
once a task, and streams its queries through it; the best k over all shards remain. With one shard this
is the plain in-memory method.

Copies of a vector in a shard are one vertex of its graph: the copy with the smallest id, its rep, has
the lists, and an answer that meets it holds all its copies.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.functions.distance import block, nearest_rows
from proxigraph.operators import kernels as K
from proxigraph.operators import resident
from proxigraph.operators.exact import top_k
from proxigraph.operators.model import DEFAULTS, SHARD_ROWS, PointSet, to_lists, to_matrix
from proxigraph.runtime import fresh_path, map_arrow, settle, ship

ROWS = "cell long, id long, rep long, vec array<double>, nbrs array<bigint>, dists array<double>, level int, upper array<array<bigint>>, start boolean, build_comps long, rounds long"
SAMPLE_ROWS = 20_000
#: What a search reads of a shard.
LOADED = ["id", "rep", "vec", "nbrs", "level", "upper", "start"]


@dataclass(frozen=True)
class Shards:
    """How points and queries find their shards. With centers, cell c owns shards first[c] to
    first[c + 1] - 1; without, a point goes to a shard by hashed id and a query to all."""

    count: int
    centers: np.ndarray | None = None
    first: np.ndarray | None = None

    def of_points(self, points: DataFrame) -> DataFrame:
        """(cell, id, vec)"""
        if self.centers is None:
            return points.select(F.pmod(F.xxhash64("id"), F.lit(self.count)).alias("cell"), "id", "vec")
        shared = points.sparkSession.sparkContext.broadcast(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = shared.value
            for b in batches:
                if b.num_rows:
                    cell = nearest_rows(to_matrix(b.column(1)), own.centers)[0][:, 0]
                    many = np.diff(own.first)[cell]
                    salt = b.column(2).to_numpy(zero_copy_only=False) % many
                    yield pa.RecordBatch.from_arrays([pa.array(own.first[cell] + salt), b.column(0), b.column(1)], ["cell", "id", "vec"])

        salted = points.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(1 << 30)).alias("salt"))
        return map_arrow(salted, run, "cell long, id long, vec array<double>")

    def of_queries(self, queries: DataFrame, probe: int | None) -> DataFrame:
        """(cell, id, vec): every query for each shard of its `probe` nearest cells (None: all)."""
        if self.centers is None or probe is None or probe >= len(self.centers):
            every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(self.count - 1).cast("long")))
            return queries.select(every.alias("cell"), "id", "vec")
        shared = queries.sparkSession.sparkContext.broadcast(self)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = shared.value
            for b in batches:
                if b.num_rows:
                    cells = nearest_rows(to_matrix(b.column(1)), own.centers, probe)[0]
                    who = np.repeat(np.arange(len(cells)), cells.shape[1])
                    c = cells.reshape(-1)
                    many = np.diff(own.first)[c]
                    rows = np.repeat(who, many)
                    shard = np.repeat(own.first[c], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                    t = pa.Table.from_batches([b]).take(pa.array(rows)).combine_chunks()
                    yield pa.RecordBatch.from_arrays([pa.array(shard), t.column("id").chunk(0), t.column("vec").chunk(0)], ["cell", "id", "vec"])

        return map_arrow(queries, run, "cell long, id long, vec array<double>")


def plan_shards(points: PointSet, shard_rows: int = SHARD_ROWS, kind: str = "cells", seed: int = 42) -> Shards:
    """One shard if the points fit; else cells of k-means on a bounded sample, cut by hashed id where a
    cell is larger than a shard, or hashed shards."""
    n = points.df.count()
    count = max(1, -(-n // shard_rows))
    if count == 1 or kind == "hash":
        return Shards(count)
    share = min(1.0, SAMPLE_ROWS / n)
    x = to_matrix(points.sample(share, seed).plain().orderBy("id").toArrow().column("vec"))
    rng = np.random.default_rng(seed)
    centers = x[np.sort(rng.choice(len(x), min(count, len(x)), replace=False))]
    for _ in range(8):
        own = nearest_rows(x, centers)[0][:, 0]
        size = np.bincount(own, minlength=len(centers))
        sums = np.zeros_like(centers)
        np.add.at(sums, own, x)
        centers = np.where(size[:, None] > 0, sums / np.maximum(size, 1)[:, None], centers)
    size = np.bincount(nearest_rows(x, centers)[0][:, 0], minlength=len(centers)) / len(x) * n
    blocks = np.maximum(1, np.ceil(1.25 * size / shard_rows)).astype(np.int64)
    return Shards(int(blocks.sum()), centers, np.concatenate([[0], np.cumsum(blocks)]))


@dataclass
class Loaded:
    """A shard: its graph over the reps (positions in the order of their ids), the reps' ids, and all
    members of each position, one after the other, by id."""

    graph: K.Graph
    ids: np.ndarray
    members: np.ndarray
    first: np.ndarray

    def expand(self, at: np.ndarray, d: np.ndarray, real: np.ndarray, k: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Per query (row): how many answers, and all answers' ids and distances, copies included; of the
        k nearest by (distance, id), or all."""
        row, col = np.nonzero(real)
        p, far = at[row, col], d[row, col]
        many = np.diff(self.first)[p]
        if (many > 1).any():
            row, far = np.repeat(row, many), np.repeat(far, many)
            place = np.repeat(self.first[p], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
            ids = self.members[place]
        else:
            ids = self.members[self.first[p]]
        order = np.lexsort((ids, far, row))
        row, ids, far = row[order], ids[order], far[order]
        if k is not None:
            keep = np.arange(len(row)) - np.searchsorted(row, row, side="left") < k
            row, ids, far = row[keep], ids[keep], far[keep]
        return np.bincount(row, minlength=len(at)), ids, far


def _load(table: pa.Table, metric: str) -> Loaded:
    order = np.lexsort((table.column("id").to_numpy(), table.column("rep").to_numpy()))
    table = table.take(pa.array(order)).combine_chunks()
    members, rep = table.column("id").to_numpy(), table.column("rep").to_numpy()
    lead = np.flatnonzero(members == rep)  # one in every group of copies, not always the first
    first = np.flatnonzero(np.diff(rep, prepend=rep[:1] - 1)) if len(rep) else lead
    table = table.take(pa.array(lead)).combine_chunks()
    ids = members[lead]
    vecs = to_matrix(table.column("vec")).T

    def lists(column) -> np.ndarray:
        column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        size = np.diff(column.offsets.to_numpy())
        out = np.full((len(column), max(1, int(size.max()) if len(size) else 1)), -1, dtype=np.int64)
        flat = column.flatten().to_numpy(zero_copy_only=False)
        row = np.repeat(np.arange(len(column)), size)
        col = np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)
        out[row, col] = np.searchsorted(ids, flat)
        return out

    nbrs = lists(table.column("nbrs"))
    starts = np.flatnonzero(table.column("start").to_numpy(zero_copy_only=False))
    graph = K.Graph(vecs, nbrs, np.zeros(nbrs.shape), int(starts[0]) if len(starts) else 0, metric)
    graph.entry = graph.start
    levels = table.column("level").to_numpy()
    top = int(levels.max()) if len(levels) else 0
    if top:
        uppers = table.column("upper").to_pylist()
        for layer in range(1, top + 1):
            graph.upper.append({int(p): (np.searchsorted(ids, np.array(uppers[p][layer - 1], dtype=np.int64)), np.zeros(len(uppers[p][layer - 1]))) for p in np.flatnonzero(levels >= layer)})
    return Loaded(graph, ids, members, np.append(first, len(members)))


def fold_copies(ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of rows x with ascending ids: the rows that are the first of their copies, and for every row which
    of these it is a copy of."""
    if not len(x):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    rows = np.ascontiguousarray(x + 0.0)  # no negative zeros
    key = rows.view(np.dtype((np.void, rows.dtype.itemsize * rows.shape[1]))).reshape(-1) if rows.shape[1] else np.zeros(len(x))
    _, first, back = np.unique(key, return_index=True, return_inverse=True)
    place = np.empty(len(first), dtype=np.int64)
    order = np.argsort(first, kind="stable")
    place[order] = np.arange(len(first))
    return first[order], place[back]


def _unload(graph: K.Graph, ids: np.ndarray, shard: int, comps: int, rounds: int, members: np.ndarray | None = None, of: np.ndarray | None = None) -> pa.Table:
    """Rows of a shard: of the graph's vertices, named ids, and of members, each a copy of vertex of[i]."""
    n = len(ids)
    keep = graph.nbrs >= 0
    size = keep.sum(axis=1)
    level = np.zeros(n, dtype=np.int32)
    upper: list[list[list[int]]] = [[] for _ in range(n)]
    for layer, rows in enumerate(graph.upper, 1):
        for p, (x, _) in rows.items():
            level[p] = layer
            upper[p].append(ids[x[x >= 0]].tolist())
    start = np.zeros(n, dtype=bool)
    if n:
        start[graph.entry if graph.upper else graph.start] = True
    if members is None:
        members, of = ids, np.arange(n)
    m, own = len(members), ids[of] == members  # a copy has no lists
    nbrs, dists = ids[graph.nbrs[keep]], graph.dists[keep]
    counts = np.where(own, size[of], 0)
    begin = np.cumsum(size) - size
    flat = np.repeat(begin[of], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    offsets = pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32))
    return pa.table({
        "cell": pa.array(np.full(m, shard)), "id": pa.array(members), "rep": pa.array(ids[of]), "vec": to_lists(np.ascontiguousarray(graph.vecs.T[of])),
        "nbrs": pa.ListArray.from_arrays(offsets, pa.array(nbrs[flat])), "dists": pa.ListArray.from_arrays(offsets, pa.array(dists[flat])),
        "level": pa.array(np.where(own, level[of], 0).astype(np.int32)), "upper": pa.array([upper[v] if o else [] for v, o in zip(of.tolist(), own.tolist(), strict=True)], pa.list_(pa.list_(pa.int64()))),
        "start": pa.array(start[of] & own), "build_comps": pa.array(np.full(m, comps)), "rounds": pa.array(np.full(m, rounds)),
    })


@dataclass(frozen=True)
class SearchResult:
    """results: qid, id, dist, rank; stats: qid, hops, dist_comps, visited (summed over shards)."""

    results: DataFrame
    stats: DataFrame


@dataclass(frozen=True)
class GraphIndex:
    method: str
    params: dict
    metric: str
    shards: Shards
    rows: DataFrame
    folder: str  # of the rows, with a folder per shard
    version: int = 0

    def edges(self) -> DataFrame:
        return self.rows.select(F.col("id").alias("src"), F.explode(F.arrays_zip("nbrs", "dists")).alias("e")).select("src", F.col("e.nbrs").alias("dst"), F.col("e.dists").alias("dist"))

    def layer_edges(self) -> DataFrame:
        """layer, src, dst of the layers above the bottom."""
        one = self.rows.select("id", F.posexplode("upper").alias("p", "l"))
        return one.select((F.col("p") + 1).alias("layer"), F.col("id").alias("src"), F.explode("l").alias("dst"))

    def fingerprint(self) -> tuple[int, int]:
        from proxigraph.operators.edges import fingerprint

        r = fingerprint(self.edges()).first()
        return r["print"], r["edges"]

    def stats(self) -> DataFrame:
        from proxigraph.operators.edges import graph_stats

        return graph_stats(self.edges())

    def build_cost(self) -> DataFrame:
        """One row: distance computations of the build's searches, and rounds, summed over shards."""
        one = self.rows.groupBy("cell").agg(F.max("build_comps").alias("c"), F.max("rounds").alias("r"))
        return one.agg(F.sum("c").alias("dist_comps"), F.sum("r").alias("rounds"))

    def search(
        self, queries: PointSet, k: int = 10, width: int = 64, eps: float | None = None, visited: str = "seen", result_from: str = "visited",
        probe: int | None = None, exclude_self: bool = False, start: str | None = None, samples: int = 16,
    ) -> SearchResult:
        """k nearest of every query by beam search in the shards it is routed to: those of its `probe`
        nearest cells, or all. start "index": the vertex that the build chose; "sample": of `samples` drawn
        vertices, the one closest to the query, which is the rule of graphs that have no vertex to start
        from (trees and descent)."""
        start = start or ("sample" if self.method in ("tree_mst", "descent") else "index")
        if width < k:
            raise ValueError("the beam must hold at least k vertices")
        metric = self.metric

        def run(shard: Loaded, q_ids: np.ndarray, q: np.ndarray):
            graph, begin = shard.graph, None
            more = 1 if exclude_self else 0
            if start == "sample" and graph.n and not graph.upper:
                drawn = K.hashed_order(shard.ids, 7)[:samples]
                begin = drawn[nearest_rows(q, graph.vecs.T[drawn], 1, metric)[0][:, 0]]
            every = k + more if eps is None and graph.n and width >= graph.n else None  # the beam holds every vertex
            if graph.upper:
                found = K.layered_search(graph, q.T, width, k + more, eps, visited, every)
            elif every is not None:
                found = K.exhausted(graph, q.T, every, begin)
            else:
                found = K.beam_search(graph, q.T, width, k + more, eps, visited, begin)
            if begin is not None:
                found.comps = found.comps + len(drawn) - 1
            at, d = found.nearest(k + more, result_from)
            size, ids, far = shard.expand(at, d, np.isfinite(d) & (at >= 0), None if exclude_self else k)
            if exclude_self:
                row = np.repeat(np.arange(len(size)), size)
                other = ids != q_ids[row]
                row, ids, far = row[other], ids[other], far[other]
                keep = np.arange(len(row)) - np.searchsorted(row, row, side="left") < k
                size, ids, far = np.bincount(row[keep], minlength=len(size)), ids[keep], far[keep]
            return size, ids, far, found

        return self._answer(queries, probe, run, k)

    def range_search(self, queries: PointSet, radius: float, width: int = 64, flood: bool = False, grow: bool = False, probe: int | None = None) -> SearchResult:
        """All points within radius that beam search meets: with flood, neighbours of points in range
        are followed until no new one is in range; with grow, the beam doubles while half of it is
        in range."""

        def run(shard: Loaded, q_ids: np.ndarray, q: np.ndarray):
            graph, w = shard.graph, width
            full = 0 < graph.n <= width  # the beam holds every vertex: there is nothing to flood, or to grow
            found = K.exhausted(graph, q.T, radius=radius) if full else K.beam_search(graph, q.T, w, 1)
            if grow:
                while w < graph.n and ((found.beam_distance <= radius).sum(axis=1) * 2 >= w).any():
                    w = min(2 * w, graph.n)
                    comps = found.comps
                    found = K.beam_search(graph, q.T, w, 1)
                    found.comps = found.comps + comps
            at = np.concatenate([found.visited, found.beam], axis=1)
            d = np.concatenate([found.distance, found.beam_distance], axis=1)
            if flood and not full:
                at, d = _flood(graph, q.T, at, d, radius, found)
            order = np.lexsort((at, d), axis=1)
            at, d = np.take_along_axis(at, order, axis=1), np.take_along_axis(d, order, axis=1)
            real = np.isfinite(d) & (at >= 0) & (d <= radius)
            real[:, 1:] &= at[:, 1:] != at[:, :-1]
            return *shard.expand(at, d, real, None), found

        return self._answer(queries, probe, run, None)

    def _answer(self, queries: PointSet, probe: int | None, run: Callable, k: int | None) -> SearchResult:
        metric = self.metric

        def ask(shard: Loaded, table: pa.Table) -> pa.RecordBatch:
            q_ids, q = table.column("id").to_numpy(), to_matrix(table.column("vec"))
            size, ids, far, found = run(shard, q_ids, q)
            offsets = pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32))
            return pa.RecordBatch.from_arrays(
                [
                    pa.array(q_ids), pa.ListArray.from_arrays(offsets, pa.array(ids)), pa.ListArray.from_arrays(offsets, pa.array(far)),
                    pa.array(found.hops), pa.array(found.comps), pa.array((found.visited >= 0).sum(axis=1) if found.processed is None else found.processed),
                ],
                ["qid", "ids", "dists", "hops", "dist_comps", "visited"],
            )

        routed = self.shards.of_queries(queries.plain(), probe)
        met = resident.answer(
            routed, self.rows, self.folder, LOADED, self.shards.count, lambda t: _load(t, metric), ask,
            "qid long, ids array<bigint>, dists array<double>, hops long, dist_comps long, visited long",
        )
        per_shard = settle(met, "search")
        found = per_shard.select("qid", F.explode(F.arrays_zip("ids", "dists")).alias("e")).select("qid", F.col("e.ids").alias("id"), F.col("e.dists").alias("dist"))
        stats = per_shard.groupBy("qid").agg(F.sum("hops").alias("hops"), F.sum("dist_comps").alias("dist_comps"), F.sum("visited").alias("visited"))
        return SearchResult(top_k(found, k) if k is not None else found, stats)

    def insert(self, points: PointSet) -> GraphIndex:
        """A new version with more points: each shard takes its arrivals in growing batches, each against
        the graph that the last one left. The old version stays as it is."""
        p = self.params
        metric, degree = self.metric, p.get("degree", DEFAULTS["degree"])
        names = ["id", "rep", "vec", "nbrs", "dists", "level", "upper", "start"]
        left = self.rows.select("cell", F.lit(0).alias("kind"), *names)
        kinds = dict(self.rows.dtypes)
        none = [F.lit(None).cast(kinds[c]).alias(c) for c in names[3:]]
        new = self.shards.of_points(points.plain()).select("cell", F.lit(1).alias("kind"), "id", F.col("id").alias("rep"), "vec", *none)
        width, alpha, m, seed = p.get("width", DEFAULTS["width"]), p.get("alpha", DEFAULTS["alpha"]), p.get("m"), p.get("seed", 42)

        def grow(table: pa.Table) -> pa.Table:
            kind = table.column("kind").to_numpy()
            old, arrived = table.filter(pa.array(kind == 0)), table.filter(pa.array(kind == 1)).sort_by("id")
            before = _load(old, metric)
            graph, lead = before.graph, before.ids
            x = to_matrix(arrived.column("vec"))
            came = arrived.column("id").to_numpy()
            both = np.concatenate([graph.vecs.T, x]) if len(lead) else x
            first, of = fold_copies(np.arange(len(both)), both)  # old vertices come first, so they stay reps
            n = len(lead)
            fresh = first[first >= n] - n  # arrivals that are vertices of their own
            # positions go by id: the places of old vertices and of new ones among all
            names_ = np.concatenate([lead, came[fresh]])
            order = np.argsort(names_, kind="stable")
            place = np.empty(len(order), dtype=np.int64)
            place[order] = np.arange(len(order))
            grown = K.empty_graph(np.concatenate([graph.vecs.T, x[fresh]])[order].T if n else x[fresh][order].T, max(degree, graph.nbrs.shape[1] if n else 0), 0, metric)
            if n:
                far = old.take(pa.array(np.flatnonzero(old.column("id").to_numpy() == old.column("rep").to_numpy()))).sort_by("id").column("dists").to_pylist()
                keep = graph.nbrs >= 0
                grown.nbrs[place[:n], : graph.nbrs.shape[1]] = np.where(keep, place[graph.nbrs], -1)
                for q, d in zip(place[:n].tolist(), far, strict=True):
                    grown.dists[q, : len(d)] = d
                grown.start = grown.entry = int(place[graph.start])
                grown.upper = [{int(place[q]): (place[t], d) for q, (t, d) in rows.items()} for rows in graph.upper]
            comps = K.insert_points(grown, names_[order], place[n:], degree, width, alpha, m, seed)
            # old members first (reps in order, each with its copies), then the arrivals
            olds = place[np.repeat(np.arange(n), np.diff(before.first))] if n else np.empty(0, np.int64)
            return _unload(grown, names_[order], table.column("cell")[0].as_py(), comps, 0, np.concatenate([before.members, came]), np.concatenate([olds, place[of[n:]]]))

        ship(self.rows.sparkSession)
        rows, folder = resident.store(left.unionByName(new).groupBy("cell").applyInArrow(grow, ROWS), "graph")
        return replace(self, rows=rows, folder=folder, version=self.version + 1)

    def save(self, path: str) -> None:
        """Rows by shard and a manifest, which is written last; every version has a folder of its own."""
        folder = f"{path}/v{self.version}"
        self.rows.repartition("cell").sortWithinPartitions("cell", "id").write.mode("overwrite").partitionBy("cell").parquet(f"{folder}/rows")
        manifest = {
            "method": self.method, "params": self.params, "metric": self.metric, "version": self.version, "count": self.shards.count,
            "centers": None if self.shards.centers is None else self.shards.centers.tolist(), "first": None if self.shards.first is None else self.shards.first.tolist(),
        }
        spark = self.rows.sparkSession
        spark.createDataFrame([(json.dumps(manifest),)], "manifest string").coalesce(1).write.mode("overwrite").json(f"{folder}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str, version: int = 0) -> GraphIndex:
        folder = f"{path}/v{version}"
        m = json.loads(spark.read.json(f"{folder}/manifest").first()["manifest"])
        shards = Shards(m["count"], None if m["centers"] is None else np.array(m["centers"]), None if m["first"] is None else np.array(m["first"]))
        rows = spark.read.schema(ROWS).parquet(f"{folder}/rows").select(*[c.split(" ")[0] for c in ROWS.split(", ")])
        return GraphIndex(m["method"], m["params"], m["metric"], shards, rows, f"{folder}/rows", m["version"])


def _flood(graph: K.Graph, q: np.ndarray, at: np.ndarray, d: np.ndarray, radius: float, found: K.Found) -> tuple[np.ndarray, np.ndarray]:
    from proxigraph.functions.distance import gathered

    rows = []
    for i in range(q.shape[1]):
        known = dict(zip(at[i][at[i] >= 0].tolist(), d[i][at[i] >= 0].tolist(), strict=True))
        front = [p for p, x in known.items() if x <= radius]
        while front:
            near = np.unique(graph.nbrs[front])
            near = np.array([p for p in near.tolist() if p >= 0 and p not in known], dtype=np.int64)
            far = gathered(q, np.array([i]), graph.vecs, near, graph.metric) if len(near) else np.empty(0)
            found.comps[i] += len(near)
            known.update(zip(near.tolist(), far.tolist(), strict=True))
            front = near[far <= radius].tolist()
        rows.append(sorted((x, p) for p, x in known.items() if x <= radius))
    most = max((len(r) for r in rows), default=0)
    out, far = np.full((len(rows), most), -1, dtype=np.int64), np.full((len(rows), most), np.inf)
    for i, r in enumerate(rows):
        out[i, : len(r)], far[i, : len(r)] = [p for _, p in r], [x for x, _ in r]
    return out, far


def _build(points: PointSet, method: str, params: dict, kernel: Callable, shard_rows: int, shard_kind: str, seed: int, joined: bool = True) -> GraphIndex:
    metric = points.metric
    shards = plan_shards(points, shard_rows, shard_kind, seed)

    def one(table: pa.Table) -> pa.Table:
        members, x = _sorted(table)
        lead, of = fold_copies(members, x)
        graph, comps, rounds = kernel(x[lead].T, members[lead], metric)
        if joined:
            K.connect(graph)
        return _unload(graph, members[lead], table.column("cell")[0].as_py(), comps, rounds, members, of)

    ship(points.df.sparkSession)
    rows, folder = resident.store(shards.of_points(points.plain()).groupBy("cell").applyInArrow(one, ROWS), "graph")
    return GraphIndex(method, params, metric, shards, rows, folder)


def _sorted(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids in ascending order, and their vectors."""
    order = np.argsort(table.column("id").to_numpy(), kind="stable")
    table = table.take(pa.array(order)).combine_chunks()
    return table.column("id").to_numpy(), to_matrix(table.column("vec"))


def alpha_graph(
    points: PointSet, degree: int = 64, width: int = 128, alpha: float = 1.2, theta: float = 0.02, rule: str = "inclusive", start: str = "medoid",
    seed: int = 42, shard_rows: int = SHARD_ROWS, shard_kind: str = "cells", engine: str = "kernel", tasks: int | None = None, joined: bool = True,
) -> GraphIndex:
    """Incremental graph with alpha pruning. rule "sequential": one point at a time; "single": all at
    once; theta 1: batches double without a cap; alpha 1: the strict prune.

    engine "kernel": a task builds a shard. "batches": all tasks (or `tasks`) build one graph together,
    batch by batch, with the same edges. "rounds": the same by joins, for graphs that no task can hold.
    joined: vertices that the start does not reach get an edge (not by rounds, nor after a single batch,
    whose graph is to show what is wrong with it)."""
    params = {"degree": degree, "width": width, "alpha": alpha, "theta": theta, "rule": rule, "seed": seed}
    if engine == "batches":
        from proxigraph.operators import batches

        made, n, spent = batches.build(points, degree, width, alpha, theta, rule, seed, tasks, joined and rule != "single")
        rows, folder = resident.store(made.withColumn("rounds", F.lit(n).cast("long")), "graph")
        rows = rows.withColumn("build_comps", F.lit(spent.value).cast("long"))
        return GraphIndex("alpha", params, points.metric, Shards(1), rows, folder)
    if engine == "rounds":
        from proxigraph.operators import rounds as R

        made, first = R.build_rounds(points, degree, width, alpha, theta, rule, seed)
        return replace(fixed_graph(points, made, first), method="alpha", params=params)
    if engine != "kernel":
        raise ValueError(f"no engine named {engine}")

    def kernel(vecs, ids, metric):
        graph, comps = K.build_alpha(vecs, ids, degree, width, alpha, theta, rule, start, seed, metric)
        return graph, comps, len(K.schedule(max(0, len(ids) - 1), max(1, int(np.ceil(theta * len(ids)))), rule))

    return _build(points, "alpha", params, kernel, shard_rows, shard_kind, seed, joined=joined and rule != "single")


def layered_graph(
    points: PointSet, m: int = 16, width: int = 128, alpha: float = 1.0, theta: float = 0.02, keep_pruned: bool = True, max_level: int | None = None,
    rule: str = "inclusive", seed: int = 42, shard_rows: int = SHARD_ROWS, shard_kind: str = "cells",
) -> GraphIndex:
    """Layered incremental graph; max_level 0 leaves only the bottom layer. rule "sequential": one point
    at a time, as under the locks of the original, whose batch interface that stands for."""

    def kernel(vecs, ids, metric):
        graph, comps = K.build_layered(vecs, ids, m, width, alpha, theta, keep_pruned, max_level, rule, seed, metric)
        return graph, comps, len(graph.upper)

    return _build(points, "layered", {"m": m, "degree": 2 * m, "width": width, "alpha": alpha, "theta": theta, "seed": seed}, kernel, shard_rows, shard_kind, seed)


def tree_mst_graph(
    points: PointSet, trees: int = 30, leaf: int = 1000, near: int | None = 10, max_degree: int = 3, degree: int = 64, alpha: float = 1.0,
    seed: int = 42, shard_rows: int = SHARD_ROWS, shard_kind: str = "cells",
) -> GraphIndex:
    """Bounded-degree spanning trees of the leaves of random cluster trees; near None: over all pairs."""

    def kernel(vecs, ids, metric):
        graph = K.build_tree_mst(vecs, ids, trees, leaf, near, max_degree, degree, alpha, seed, metric)
        return graph, graph.comps, trees

    return _build(points, "tree_mst", {"trees": trees, "leaf": leaf, "near": near, "max_degree": max_degree, "degree": degree, "alpha": alpha, "seed": seed}, kernel, shard_rows, shard_kind, seed)


def descent_graph(
    points: PointSet, trees: int = 10, leaf: int = 100, k: int = 40, degree: int = 64, alpha: float = 1.2, cap: int | None = 2000, delta: float = 0.001,
    max_rounds: int = 20, init: str = "trees", block: int = 512, seed: int = 42, shard_rows: int = SHARD_ROWS, shard_kind: str = "cells",
) -> GraphIndex:
    """Nearest-neighbour descent from the leaves of random hyperplane trees (or a random graph)."""

    def kernel(vecs, ids, metric):
        graph, rounds = K.build_descent(vecs, ids, trees, leaf, k, degree, alpha, cap, delta, max_rounds, init, seed, metric, block)
        return graph, graph.comps, rounds

    return _build(points, "descent", {"trees": trees, "leaf": leaf, "k": k, "degree": degree, "alpha": alpha, "cap": cap, "delta": delta, "init": init, "seed": seed}, kernel, shard_rows, shard_kind, seed)


def hybrid_graph(
    points: PointSet, trees: int = 10, leaf: int = 200, near: int | None = 10, max_degree: int = 3, degree: int = 64, width: int = 128, alpha: float = 1.2,
    theta: float = 0.02, seed: int = 42, shard_rows: int = SHARD_ROWS, shard_kind: str = "cells",
) -> GraphIndex:
    """Tree edges as the first snapshot, then one pass of insertions over all points."""

    def kernel(vecs, ids, metric):
        first = K.build_tree_mst(vecs, ids, trees, leaf, near, max_degree, degree, 1.0, seed, metric)
        graph, comps = K.build_alpha(vecs, ids, degree, width, alpha, theta, "inclusive", "medoid", seed, metric, first)
        return graph, comps + first.comps, trees

    return _build(points, "hybrid", {"trees": trees, "leaf": leaf, "degree": degree, "width": width, "alpha": alpha, "seed": seed}, kernel, shard_rows, shard_kind, seed)


def fixed_graph(points: PointSet, edges: DataFrame, start: int, joined: bool = False) -> GraphIndex:
    """An index of a given graph (src, dst, dist), in one shard. joined: vertices that the start does not
    reach get an edge."""
    lists = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst"))).alias("c"))
    rows = points.plain().join(lists, F.col("id") == F.col("src"), "left").select(
        F.lit(0).cast("long").alias("cell"), "id", F.col("id").alias("rep"), "vec", F.coalesce("c.dst", F.array().cast("array<bigint>")).alias("nbrs"), F.coalesce("c.dist", F.array().cast("array<double>")).alias("dists"),
        F.lit(0).alias("level"), F.array().cast("array<array<bigint>>").alias("upper"), (F.col("id") == start).alias("start"), F.lit(0).cast("long").alias("build_comps"), F.lit(0).cast("long").alias("rounds"),
    )
    metric = points.metric

    def one(table: pa.Table) -> pa.Table:
        table = table.sort_by("id").combine_chunks()
        loaded = _load(table.select(LOADED), metric)
        graph = loaded.graph
        r, c = np.nonzero(graph.nbrs >= 0)
        graph.dists[graph.nbrs < 0] = np.inf
        graph.dists[r, c] = table.column("dists").combine_chunks().flatten().to_numpy()
        K.connect(graph)
        return _unload(graph, loaded.ids, 0, 0, 0)

    if joined:
        ship(points.df.sparkSession)
    rows = rows.groupBy("cell").applyInArrow(one, ROWS) if joined else rows.coalesce(1)
    return GraphIndex("fixed", {}, metric, Shards(1), *resident.store(rows, "graph"))


BUILDERS = {"alpha": alpha_graph, "layered": layered_graph, "tree_mst": tree_mst_graph, "descent": descent_graph, "hybrid": hybrid_graph}


def index_path(spark: SparkSession, name: str) -> str:
    return fresh_path(spark, f"index-{name}")
