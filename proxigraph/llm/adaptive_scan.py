"""Approximate nearest neighbours by adaptive scans of dimensions.

Vectors are put into lists around centroids; inner products become distances by one more dimension,
which gives every vector the same norm. A query visits the lists that, by a normal model of the
scores in each list, hold nearly all of its neighbours: on clustered data few, on noise most.

Vectors are rotated to the axes of largest variance and kept in blocks of columns. A query reads the
first block of its candidates, tests each candidate, goes on to the next block with those that passed,
and so on; what passes the last test is scored exactly. The hypothesis that a candidate is within the
query's threshold t is rejected once the distance read so far exceeds a critical share of t. The
critical shares are quantiles over true neighbours of a sample, so that all tests together reject at
most LOSS of them. The list that promises most is scanned first, and what it yields tightens t.

Lists are cut into blocks of bounded size by hashed id, so a list of any size, as one of many copies
of a vector, is shared by many tasks; small lists share a cell, to which a query is sent once.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.llm.vector_cells import Sample, best, clean_vectors, deal_queries, in_cells, least_scores, matrix, query_rows, sample, settle
from proxigraph.runtime import map_arrow

#: Rows of a cell, at most about.
CELL_ROWS = 8192
COLUMNS = 16
#: Share of the true neighbours that the tests may abandon.
LOSS = 0.01
#: Queries from the sample on which the tests are calibrated.
CALIBRATION_ROWS = 256
#: Share of the neighbours that the visited lists should hold by the model.
COVERAGE = 0.98
LEAST_LISTS, MOST_LISTS = 4, 1024
ITERATIONS = 8
SEED = 42
FOUND = "query_id long, vec_id long, score double"


def _phi(x: np.ndarray) -> np.ndarray:
    """Upper tail of the normal distribution, by its logistic approximation."""
    return 1.0 / (1.0 + np.exp(np.clip(1.5976 * x + 0.07056 * x ** 3, -500, 500)))


class Lists:
    """Centroids, sizes and spreads of the lists, their cells, the rotation and the critical shares of
    the tests, fitted on a bounded sample."""

    def __init__(self, known: Sample, k: int = 20):
        rng = np.random.default_rng(SEED)
        x = known.rows
        n, d = x.shape
        # thresholds come from an eighth of all rows at most, so that more than k rows reach them
        thin = slice(None, None, max(1, -(-8 * n // max(1, known.count))))
        self.thin = Sample(known.ids[thin], known.rows[thin], known.count, known.longest)
        self.known, self.k = known, int(min(MOST_LISTS, max(1, math.sqrt(known.count) / 4), max(1, n // 8)))
        centers = x[np.sort(rng.choice(n, self.k, replace=False))]
        for _ in range(ITERATIONS):
            own = self._nearest(x, centers)
            size = np.bincount(own, minlength=self.k)
            sums = np.zeros_like(centers)
            np.add.at(sums, own, x)
            centers = np.where(size[:, None] > 0, sums / np.maximum(size, 1)[:, None], centers)
        self.centers = centers
        own = self._nearest(x, centers)
        self.size = np.bincount(own, minlength=self.k) * (known.count / max(1, n))
        apart = np.bincount(own, weights=((x - centers[own]) ** 2).sum(axis=1), minlength=self.k)
        self.variance = apart / np.maximum(np.bincount(own, minlength=self.k), 1) / d
        self.blocks = np.maximum(1, np.ceil(self.size / CELL_ROWS)).astype(np.int64)
        # a large list owns its cells; small ones, in order, share a cell until it is full
        self.first = np.zeros(self.k, dtype=np.int64)
        cell, held = -1, math.inf
        for j, (size, blocks) in enumerate(zip(self.size.tolist(), self.blocks.tolist(), strict=True)):
            if blocks > 1 or held + size > CELL_ROWS:
                cell, held = cell + 1, 0
            self.first[j] = cell
            held += size
            if blocks > 1:
                cell, held = cell + blocks - 1, math.inf
        self.cells = cell + 1
        self.rotation = np.eye(d + 1)
        turned = self.lifted(x)
        self.rotation = np.linalg.eigh(np.cov(turned.T.astype(np.float64)).reshape(d + 1, d + 1))[1][:, ::-1]
        self.cuts = [*range(COLUMNS, d + 1, COLUMNS), d + 1]
        self.shares = self._critical(x, k)

    def _shares(self, q: np.ndarray, x: np.ndarray, near: np.ndarray) -> np.ndarray:
        """Of the distances from rows q to rows x[near], what is read by the end of each column block but
        the last (queries x neighbours x blocks)."""
        apart = np.cumsum((self.lifted(q, query=True)[:, None].astype(np.float64) - self.lifted(x)[near]) ** 2, axis=2)
        return apart[:, :, [c - 1 for c in self.cuts[:-1]]] / np.maximum(apart[:, :, -1:], 1e-30)

    def _critical(self, x: np.ndarray, k: int) -> np.ndarray:
        """For each column block, which share of its whole distance a true neighbour has at most by then."""
        tests, step = len(self.cuts) - 1, max(1, -(-len(x) // CALIBRATION_ROWS))
        q = x[::step]
        scores = q @ x.T
        scores[np.arange(len(q)), np.arange(len(q)) * step] = -np.inf
        near = np.argsort(-scores, axis=1)[:, : min(k, len(x) - 1)]
        if not tests or not near.size:
            return np.ones(len(self.cuts))
        return np.append(np.quantile(self._shares(q, x, near).reshape(-1, tests), 1 - LOSS / tests, axis=0), 1.0)

    def terms(self, q: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
        """A row per query: the score its k-th best reaches at least, and its critical shares, which are
        no less than what its own neighbours among the threshold rows need."""
        least = least_scores(q, ids, self.thin, k)
        shares = np.tile(self.shares, (len(q), 1))
        if len(self.thin.ids) > k and len(self.cuts) > 1:
            scores = q @ self.thin.rows.T
            scores[ids[:, None] == self.thin.ids[None, :]] = -np.inf
            near = np.argpartition(-scores, k - 1, axis=1)[:, :k]
            shares[:, :-1] = np.maximum(shares[:, :-1], self._shares(q, self.thin.rows, near).max(axis=1))
        return np.column_stack([least, shares])

    @staticmethod
    def _nearest(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
        return ((centers ** 2).sum(axis=1) - 2 * (x @ centers.T)).argmin(axis=1)

    def assign(self, x: np.ndarray) -> np.ndarray:
        return self._nearest(x, self.centers)

    def probes(self, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Which lists each query visits (boolean matrix), and how many neighbours each promises."""
        mean = q @ self.centers.T
        sigma = np.sqrt(np.maximum((q ** 2).sum(axis=1)[:, None] * self.variance, 1e-30))
        low, high = (mean - 12 * sigma).min(axis=1), (mean + 12 * sigma).max(axis=1)
        for _ in range(40):  # the score above which the model expects k vectors
            mid = (low + high) / 2
            over = (self.size * _phi((mid[:, None] - mean) / sigma)).sum(axis=1) > k
            low, high = np.where(over, mid, low), np.where(over, high, mid)
        hits = self.size * _phi((low[:, None] - mean) / sigma) + 1e-12
        order = np.argsort(-hits, axis=1, kind="stable")
        before = np.cumsum(np.take_along_axis(hits, order, axis=1), axis=1) - np.take_along_axis(hits, order, axis=1)
        rows = np.take_along_axis(np.broadcast_to(self.size, hits.shape), order, axis=1)
        few = np.cumsum(rows, axis=1) - rows < 10 * k
        visit = (before < COVERAGE * hits.sum(axis=1, keepdims=True)) | (np.arange(self.k) < LEAST_LISTS) | few
        out = np.zeros_like(visit)
        np.put_along_axis(out, order, visit, axis=1)
        return out, hits

    def lifted(self, x: np.ndarray, query: bool = False) -> np.ndarray:
        """Rotated vectors with the further dimension; distances to queries fall as scores rise."""
        more = np.zeros(len(x)) if query else np.sqrt(np.maximum(self.known.longest - (x ** 2).sum(axis=1), 0))
        return (np.column_stack([x, more]) @ self.rotation).astype(np.float32)


class Cell:
    """The rows of some lists, sorted by list, with their rotated vectors in blocks of columns."""

    def __init__(self, lists: Lists, ids: np.ndarray, x: np.ndarray):
        own = lists.assign(x)
        order = np.lexsort((ids, own))
        self.lists, self.ids, self.x = lists, ids[order], x[order]
        self.names, self.begin, self.place = np.unique(own[order], return_index=True, return_inverse=True)
        self.end = np.append(self.begin[1:], len(ids))
        turned = lists.lifted(self.x)
        self.columns = [np.ascontiguousarray(turned[:, a:b]) for a, b in zip([0, *lists.cuts], lists.cuts, strict=False)]
        self.norms = (self.columns[0] ** 2).sum(axis=1)
        self.read = self.all = 0  # components read, and there were

    def _surviving(self, q: list[np.ndarray], rows: np.ndarray, first: np.ndarray, limit: float, shares: np.ndarray) -> np.ndarray:
        """Those of the rows, whose distances in the first block are given, that no test abandons."""
        self.read += len(rows) * len(q[0])
        part = first[rows]
        for j, share in enumerate(shares.tolist()):
            if j:
                near = self.columns[j].take(rows, axis=0)
                near -= q[j]
                self.read += near.size
                part = part + np.einsum("ij,ij->i", near, near)
            alive = np.flatnonzero(part <= limit * share)
            rows, part = rows.take(alive), part.take(alive)
            if not len(rows):
                break
        return rows

    def _search_one(self, q: np.ndarray, turned: np.ndarray, first: np.ndarray, own_id: int, visit: np.ndarray, promise: np.ndarray, terms: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        rows, scores = np.empty(0, np.int64), np.empty(0)
        mine = np.flatnonzero(visit[self.names])
        if not len(mine):
            return rows, scores
        columns = np.split(turned, self.lists.cuts[:-1])
        norm, least, shares = float(q @ q) + self.lists.known.longest, float(terms[0]), terms[1:]
        best = mine[promise[self.names[mine]].argmax()]
        others = visit[self.names]
        others[best] = False
        for part in (np.arange(self.begin[best], self.end[best]), np.flatnonzero(others[self.place])):
            limit = norm - 2 * least + norm * 1e-5 if least > -np.inf else np.inf
            self.all += len(part) * len(turned)
            found = self._surviving(columns, part, first, limit, shares)
            found = found[self.ids[found] != own_id]
            rows, scores = np.concatenate([rows, found]), np.concatenate([scores, np.einsum("ij,j->i", self.x[found], q)])
            top = np.lexsort((self.ids[rows], -scores))[:k]
            rows, scores = rows[top], scores[top]
            if len(rows) == k:
                least = max(least, float(scores[-1]))
        return rows, scores

    def search(self, q: np.ndarray, q_ids: np.ndarray, terms: np.ndarray, k: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """Of each query, (rows, scores) of up to k best of the visited lists, best first."""
        visit, promise = self.lists.probes(q, k)
        turned = self.lists.lifted(q, query=True)
        wide = self.columns[0].shape[1]
        out = []
        for lo in range(0, len(q), 128):
            head = turned[lo: lo + 128, :wide]
            first = self.norms - 2 * (head @ self.columns[0].T) + (head ** 2).sum(axis=1)[:, None]
            out += [self._search_one(q[i], turned[i], first[i - lo], int(q_ids[i]), visit[i], promise[i], terms[i], k) for i in range(lo, min(lo + 128, len(q)))]
        return out


def search(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 20, k: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score: for each row whose id is divisible by `every`, up to k rows of
    largest inner product among all others, nearest first, ties to the smaller id.

    Null, zero and unusable vectors take no part (see clean_vectors). An empty table gives an empty
    result, one vector none; fewer candidates than k are all returned.
    """
    vecs = settle(clean_vectors(vectors, id_col, vec_col), "vectors")
    known = sample(vecs)
    spark = vectors.sparkSession
    if known.count < 2 or len(known.ids) < 1:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    shared = spark.sparkContext.broadcast(Lists(known, k))

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists = shared.value
        for batch in batches:
            if batch.num_rows:
                own = lists.assign(matrix(batch.column(1)))
                salt = batch.column(2).to_numpy(zero_copy_only=False) % lists.blocks[own]
                yield pa.RecordBatch.from_arrays([pa.array(lists.first[own] + salt), batch.column(0), batch.column(1)], ["cell", "id", "data"])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists = shared.value
        for batch in batches:
            if batch.num_rows:
                q, ids = matrix(batch.column(1)), batch.column(0).to_numpy(zero_copy_only=False)
                terms = lists.terms(q, ids, k)
                who, which = np.nonzero(lists.probes(q, k)[0])
                many = lists.blocks[which]
                who = np.repeat(who, many)
                cells = np.repeat(lists.first[which], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                who, cells = np.unique(np.stack([who, cells]), axis=1)
                data = [v + terms[i].tobytes() for i, v in enumerate(batch.column(1).to_pylist())]
                yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(ids[who]), pa.array([data[i] for i in who], pa.binary())], ["cell", "id", "data"])

    def load(ids: np.ndarray, datas: list[bytes]) -> Cell:
        return Cell(shared.value, ids, matrix(datas))

    def probe(cell: Cell, ids: np.ndarray, datas: list[bytes]) -> pa.RecordBatch:
        both = matrix(datas)
        d = cell.x.shape[1]
        q, terms = np.ascontiguousarray(both[:, :d]), both[:, d:]
        found = cell.search(q, ids, terms, k)
        rows = np.concatenate([r for r, _ in found])
        who = np.repeat(ids, [len(r) for r, _ in found])
        return pa.RecordBatch.from_arrays([pa.array(who), pa.array(cell.ids[rows]), pa.array(np.concatenate([s for _, s in found]))], ["query_id", "vec_id", "score"])

    salted = vecs.select("id", "data", F.pmod(F.xxhash64("id", F.lit(7)), F.lit(1 << 30)).alias("salt"))
    rows = map_arrow(salted, assign, "cell long, id long, data binary")
    queries = query_rows(vecs, every)
    routed = map_arrow(queries, route, "cell long, id long, data binary")
    return best(in_cells(rows, routed, deal_queries(known.count // every), load, probe, FOUND), k)
