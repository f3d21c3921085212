"""Quantisers: scalar bytes, and product codes with table distances and exact re-ranking, over all points
or over the residuals in inverted lists."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.distance import block, expression, gathered, nearest_rows
from proxigraph.functions.prng import draw
from proxigraph.operators import resident
from proxigraph.operators.exact import nearest_of, top_k
from proxigraph.operators.inverted import LIST_ROWS, InvertedIndex
from proxigraph.operators.model import PointSet, to_lists, to_matrix
from proxigraph.runtime import map_arrow, settle

SAMPLE_ROWS = 20_000
#: Table distances that a kernel holds at once.
PAIRS = 4 << 20


def sq8(points: PointSet, scale: float = 127.0) -> PointSet:
    """Components scaled, rounded and clamped to signed bytes."""
    byte = F.transform(points.vec, lambda x: F.greatest(F.lit(-127), F.least(F.lit(127), F.round(x.cast("double") * scale))).cast("tinyint"))
    return PointSet(points.df.withColumn(points.vec, byte), points.id, points.vec, points.metric)


@dataclass(frozen=True)
class ProductCodes:
    """Codebooks of equal slices of the vector: parts x codes x (dims / parts)."""

    books: np.ndarray

    @classmethod
    def train(cls, points: PointSet, parts: int = 8, codes: int = 16, iters: int = 8, seed: int = 42) -> ProductCodes:
        """Codebooks from a bounded sample by draw, k-means in each slice."""
        if points.metric != "l2":
            raise ValueError("product codes are tables of l2 distances")
        n = points.df.count()
        share = min(1.0, SAMPLE_ROWS / max(1, n))
        rows = points.sample(share, seed).plain().withColumn("h", draw(seed, "id")).orderBy("h", "id").toArrow()
        x = to_matrix(rows.column("vec"))
        books = []
        for part in np.split(x, parts, axis=1):
            centers = part[: min(codes, len(part))].copy()
            for _ in range(iters):
                own = nearest_rows(part, centers)[0][:, 0]
                for c in range(len(centers)):
                    if (own == c).any():
                        centers[c] = np.round(part[own == c] * (1 << 20)).sum(axis=0) / (1 << 20) / (own == c).sum()
            books.append(centers)
        return cls(np.stack(books))

    def encode(self, points: PointSet) -> DataFrame:
        """id, codes array<int>"""
        shared = points.df.sparkSession.sparkContext.broadcast(self.books)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            books = shared.value
            for b in batches:
                if b.num_rows:
                    x = np.split(to_matrix(b.column(1)), len(books), axis=1)
                    codes = np.stack([nearest_rows(p, c)[0][:, 0] for p, c in zip(x, books, strict=True)], axis=1)
                    yield pa.RecordBatch.from_arrays([b.column(0), to_lists(codes, pa.int32())], ["id", "codes"])

        return map_arrow(points.plain(), run, "id long, codes array<int>")

    def closest(self, routed: DataFrame, rows: DataFrame, folder: str, cells: int, most: int, k: int, whole: bool) -> DataFrame:
        """qid, id, dist, rank: of the queries routed to cells of (id, vec, codes), the k nearest by exact distance of
        each one's `most` best by table distances. A routed query is what the tables are made of, then its
        vector. Cells hold the vectors, so a candidate leaves its cell with both distances; with `whole`, `most`
        leaves none out, and a cell gives its k nearest only."""
        books = self.books

        def load(table: pa.Table):
            table = table.take(pa.array(np.argsort(table.column("id").to_numpy(), kind="stable")))
            return table.column("id").to_numpy(), to_matrix(table.column("vec")), to_matrix(table.column("codes")).astype(np.int64)

        def ask(held, table: pa.Table) -> pa.RecordBatch:
            ids, x, codes = held
            q_ids, both = table.column("id").to_numpy(), to_matrix(table.column("vec"))
            coded, q = both[:, : -x.shape[1]], both[:, -x.shape[1]:]
            m, out = min(most, len(ids)), []
            step = max(1, PAIRS // len(ids))
            for lo in range(0, len(q), step):
                part = np.split(coded[lo: lo + step], len(books), axis=1)
                if whole:
                    r, i, d = nearest_of(q_ids[lo: lo + step], q[lo: lo + step], ids, x, "l2", k)
                    out.append((r + lo, i, d, np.zeros(len(r))))
                    continue
                far = sum((block(p, c) ** 2)[:, codes[:, j]] for j, (p, c) in enumerate(zip(part, books, strict=True)))
                # all below the m-th distance, and of those at it the least ids
                last = np.partition(far, m - 1, axis=1)[:, m - 1: m]
                sure, even = far < last, far == last
                even &= np.cumsum(even, axis=1) <= m - sure.sum(axis=1, keepdims=True)
                r, c = np.nonzero(sure | even)
                out.append((r + lo, ids[c], gathered(q[lo: lo + step].T, r, x.T, c), far[r, c]))
            r, i, d, t = (np.concatenate([o[j] for o in out]) for j in range(4))
            return pa.RecordBatch.from_arrays([pa.array(q_ids[r]), pa.array(i), pa.array(d), pa.array(t)], ["qid", "id", "dist", "table"])

        met = resident.answer(routed, rows, folder, ["id", "vec", "codes"], cells, load, ask, "qid long, id long, dist double, table double")
        if not whole:
            order = Window.partitionBy("qid").orderBy(F.sqrt("table"), "id")
            met = met.withColumn("_n", F.row_number().over(order)).filter(F.col("_n") <= most)
        return top_k(settle(met.select("qid", "id", "dist"), "rerank"), k)

    def search(self, coded: DataFrame, points: PointSet, queries: PointSet, k: int = 10, rerank: int = 50) -> DataFrame:
        """qid, id, dist, rank: the `rerank` best by table distances of the codes, re-ranked exactly. All
        codes are scanned, in cells by hashed id that stay where they are; the queries go to every cell."""
        n = coded.count()
        cells = max(1, -(-n // LIST_ROWS))
        dealt = coded.join(points.plain(), "id").select(F.pmod(F.xxhash64("id"), F.lit(cells)).alias("cell"), "id", "vec", "codes").repartition("cell")
        rows, folder = resident.store(dealt, "codes")
        every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(cells - 1).cast("long"))).alias("cell")
        routed = queries.plain().select(every, "id", F.concat("vec", "vec").alias("vec"))
        return self.closest(routed, rows, folder, cells, rerank, k, rerank >= n)


def reranked(close: DataFrame, points: PointSet, queries: PointSet, k: int) -> DataFrame:
    """qid, id, dist, rank: the k nearest of the candidates (qid, id) by exact distance."""
    a = queries.plain().select(F.col("id").alias("qid"), F.col("vec").alias("a"))
    b = points.plain().select("id", F.col("vec").alias("b"))
    return top_k(close.join(a, "qid").join(b, "id").select("qid", "id", expression(points.metric, "b", "a").alias("dist")), k)


@dataclass(frozen=True)
class CodedLists:
    """Inverted lists of product codes: a member's code is that of its residual, what is left of it after
    its list's centroid is taken away."""

    lists: InvertedIndex
    codes: ProductCodes
    rows: DataFrame  # cell, id, vec, codes
    folder: str

    @classmethod
    def build(cls, points: PointSet, cells: int, iters: int = 10, parts: int = 8, codes: int = 16, seed: int = 42) -> CodedLists:
        lists = InvertedIndex.build(points, cells, iters, seed)
        residuals = cls._residual(lists.postings.select("list", "cell", "id", "vec"), lists)
        left = PointSet(settle(residuals, "residuals"))
        books = ProductCodes.train(left, parts, codes, seed=seed)
        coded = books.encode(left).join(lists.postings.select("id", "cell", "vec"), "id").select("cell", "id", "vec", "codes")
        return cls(lists, books, *resident.store(coded.repartition("cell").sortWithinPartitions("cell", "id"), "codes"))

    @staticmethod
    def _residual(rows: DataFrame, lists: InvertedIndex) -> DataFrame:
        centers = lists.cells.select(F.col("cell").alias("list"), "centroid")
        return rows.join(centers, "list").select("cell", "id", F.zip_with("vec", "centroid", lambda x, c: x - c).alias("vec"))

    def search(self, points: PointSet, queries: PointSet, k: int = 10, probe: int = 4, rerank: int = 50) -> DataFrame:
        """qid, id, dist, rank: the `rerank` best by table distances in the `probe` nearest lists, re-ranked
        exactly."""
        centers = self.lists.cells.select(F.col("cell").alias("list"), "centroid")
        met = self.lists.routed(self.lists.probed(queries, probe)).join(centers, "list")
        routed = met.select("cell", "id", F.concat(F.zip_with("vec", "centroid", lambda x, c: x - c), "vec").alias("vec"))
        return self.codes.closest(routed, self.rows, self.folder, int(self.lists.first[-1]), rerank, k, rerank >= points.df.count())


def graph_search_reranked(coarse, points: PointSet, queries: PointSet, k: int = 10, rerank: int = 50, scale: float = 127.0, **params) -> DataFrame:
    """qid, id, dist, rank: a graph over sq8(points), searched with sq8 queries for `rerank` candidates,
    which are ranked anew by their exact distances."""
    near = coarse.search(sq8(queries, scale), rerank, max(rerank, params.pop("width", rerank)), **params).results.select("qid", "id")
    return reranked(near, points, queries, k)
