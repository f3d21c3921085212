"""Exact top-k inner products over integer vectors by best-first search of M-trees.

One more dimension gives all vectors the same norm, so that the Euclidean distance to a query falls
as the inner product rises, and a metric tree finds the largest products exactly. Rows are dealt to the
nearest of some routing vectors from a sample, and those of one, if many, by hashed id to shards of
bounded size; a shard's covering radius is taken over all its rows, and a query only visits the shards
whose radius admits a row above its threshold (on data without clusters, as noise, that is every shard).
Each shard becomes an M-tree of pages: an inner page holds routing vectors with covering radii, distances
to the parent's routing vector and child pages; a leaf page holds vectors with their parent distances.
The pages are written as a table. A search takes pages from a queue in the order of the least distance
they may hold; an entry whose stored parent distance and radius already prove it too far costs no
distance computation.

Products are summed as doubles, which is exact for integers below 2**53; larger vectors are refused.
"""

from __future__ import annotations

import heapq
import math
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.llm.vector_cells import Sample, best, clean_vectors, deal_queries, in_cells, least_scores, matrix, query_rows, sample, settle, spread
from proxigraph.runtime import map_arrow

SHARD_ROWS = 8192
PAGE_ENTRIES = 512
FANOUT = 32
#: Routing vectors of the shards, at most.
MOST_ROUTERS = 4096
SCALE = 64
SEED = 42
FOUND = "query_id long, vec_id long, score long"


def quantise(x: np.ndarray) -> np.ndarray:
    return np.floor(SCALE * x)


class Tree:
    """Pages by number; page 0 is the root. A page is (is_leaf, vectors, parent distances, radii,
    child pages or ids)."""

    def __init__(self, longest: float, pages: dict[int, tuple] | None = None):
        self.longest, self.pages = longest, pages if pages is not None else {}
        self.computed = self.avoided = 0

    def _apart(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Distances of rows x to the vector y, the further dimension included."""
        up = np.sqrt(np.maximum(self.longest - (x ** 2).sum(axis=1), 0))
        one = math.sqrt(max(self.longest - float((y ** 2).sum()), 0.0))
        return np.sqrt(((x - y) ** 2).sum(axis=1) + (up - one) ** 2)

    @classmethod
    def build(cls, ids: np.ndarray, x: np.ndarray, longest: float) -> Tree:
        tree = cls(longest)
        order = np.argsort(ids)
        tree._fill(ids[order], x[order], None, np.random.default_rng(SEED))
        return tree

    def _fill(self, ids: np.ndarray, x: np.ndarray, router: np.ndarray | None, rng) -> int:
        page = len(self.pages)
        self.pages[page] = ()
        above = self._apart(x, router) if router is not None else np.zeros(len(x))
        if len(ids) <= PAGE_ENTRIES:
            self.pages[page] = (True, x, above, np.zeros(len(x)), ids)
            return page
        k = min(FANOUT, -(-len(ids) // PAGE_ENTRIES) * 2)
        seeds = np.sort(rng.choice(len(ids), k, replace=False))
        apart = np.stack([self._apart(x, x[s]) for s in seeds])
        own = apart.argmin(axis=0)
        if np.bincount(own, minlength=k).max() == len(ids):  # copies of one vector
            own = np.arange(len(ids)) % k
        used = np.unique(own)
        kids, radii = [], []
        for j in used:
            mine = own == j
            radii.append(apart[j][mine].max())
            kids.append(self._fill(ids[mine], x[mine], x[seeds[j]], rng))
        routers = x[seeds[used]]
        self.pages[page] = (False, routers, self._apart(routers, router) if router is not None else np.zeros(len(used)), np.array(radii), np.array(kids, dtype=np.int64))
        return page

    def search(self, q: np.ndarray, own_id: int, k: int, least: float = -np.inf) -> tuple[np.ndarray, np.ndarray]:
        """(ids, scores) of the k largest products of at least `least`, without own_id, best first."""
        norm = float(q @ q) + self.longest
        slack = 1e-7 * (1 + math.sqrt(norm))
        far = math.sqrt(max(norm - 2 * least, 0.0)) + slack if least > -np.inf else math.inf
        ids, scores = np.empty(0, np.int64), np.empty(0)
        queue: list[tuple[float, int, float]] = [(0.0, 0, math.nan)]
        while queue:
            bound, number, parent = heapq.heappop(queue)
            if bound > far:
                break
            leaf, x, above, radii, names = self.pages[number]
            if parent == parent and far < math.inf:
                near = np.abs(parent - above) - radii <= far
                self.avoided += len(near) - int(np.count_nonzero(near))
                if not near.all():
                    x, radii, names = x[near], radii[near], names[near]
                    if not len(x):
                        continue
            dots = x @ q
            self.computed += len(dots)
            if leaf:
                good = (dots >= least) & (names != own_id)
                if good.any():
                    ids, scores = np.concatenate([ids, names[good]]), np.concatenate([scores, dots[good]])
                    if len(ids) >= k:
                        top = np.lexsort((ids, -scores))[:k]
                        ids, scores = ids[top], scores[top]
                        least = scores[-1]
                        far = math.sqrt(max(norm - 2 * least, 0.0)) + slack
            else:
                d = np.sqrt(np.maximum(norm - 2 * dots, 0))
                low = np.maximum(d - radii, bound)
                for b, c, e in zip(low.tolist(), names.tolist(), d.tolist(), strict=True):
                    if b <= far:
                        heapq.heappush(queue, (b, c, e))
        top = np.lexsort((ids, -scores))[:k]
        return ids[top], scores[top]


class Shards:
    """Routing vectors and the shards that each owns, from a bounded sample."""

    def __init__(self, known: Sample):
        rng = np.random.default_rng(SEED)
        wanted = -(-known.count // SHARD_ROWS)
        self.longest = known.longest
        self.routers = known.rows[np.sort(rng.choice(len(known.rows), min(wanted, len(known.rows), MOST_ROUTERS), replace=False))]
        share = np.bincount(self.nearest(known.rows), minlength=len(self.routers)) / len(known.rows)
        self.blocks = np.maximum(1, np.ceil(1.1 * share * known.count / SHARD_ROWS)).astype(np.int64)
        self.first = np.concatenate([[0], np.cumsum(self.blocks)])
        self.count = int(self.first[-1])

    def apart(self, x: np.ndarray, query: bool = False) -> np.ndarray:
        """Distances of rows to all routers; a query has no further dimension."""
        up = np.zeros(len(x)) if query else np.sqrt(np.maximum(self.longest - (x ** 2).sum(axis=1), 0))
        own = np.sqrt(np.maximum(self.longest - (self.routers ** 2).sum(axis=1), 0))
        near = (x ** 2).sum(axis=1)[:, None] + (self.routers ** 2).sum(axis=1) - 2 * (x @ self.routers.T)
        return np.sqrt(np.maximum(near + (up[:, None] - own) ** 2, 0))

    def nearest(self, x: np.ndarray) -> np.ndarray:
        return self.apart(x).argmin(axis=1)


def build_pages(vecs: DataFrame, shards: Shards) -> DataFrame:
    """(cell, id, data): the pages of every shard's tree, id being the page's number; page -1 is the
    shard's covering radius."""
    shared = vecs.sparkSession.sparkContext.broadcast(shards)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            if batch.num_rows:
                router = own.nearest(matrix(batch.column(1)))
                cell = own.first[router] + batch.column(2).to_numpy(zero_copy_only=False) % own.blocks[router]
                yield pa.RecordBatch.from_arrays([pa.array(cell), batch.column(0), batch.column(1)], ["cell", "id", "data"])

    placed = map_arrow(vecs.select("id", "data", spread("id", F.lit(1 << 30)).alias("salt")), place, "cell long, id long, data binary")
    dealt = placed.repartition("cell").sortWithinPartitions("cell")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, datas = None, [], []

        def flush() -> Iterator[pa.RecordBatch]:
            if datas:
                x, own = matrix(datas), shared.value
                tree = Tree.build(np.array(ids, dtype=np.int64), x, own.longest)
                radius = own.apart(x)[:, int(np.searchsorted(own.first, now, side="right")) - 1].max()
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([now] * (len(tree.pages) + 1), pa.int64()), pa.array([-1, *tree.pages], pa.int64()),
                        pa.array([pickle.dumps(p) for p in (float(radius), *tree.pages.values())], pa.binary()),
                    ],
                    ["cell", "id", "data"],
                )

        for batch in batches:
            for cell, key, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if cell != now:
                    yield from flush()
                    now, ids, datas = cell, [], []
                ids.append(key)
                datas.append(data)
        yield from flush()

    return map_arrow(dealt, run, "cell long, id long, data binary")


def search(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 20, k: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score (long): for each row whose id is divisible by `every`, the k rows
    with the largest inner product of floor(64 x) among all others, ties to the smaller id; exact.

    Null and unusable vectors take no part (see clean_vectors), zero vectors do. An empty table gives
    an empty result; fewer candidates than k are all returned. Vectors whose products may reach 2**53
    raise an error.
    """
    vecs = settle(clean_vectors(vectors, id_col, vec_col, quantise, keep_zero=True), "integer-vectors")
    known = sample(vecs)
    spark = vectors.sparkSession
    if known.count < 2 or len(known.ids) < 1:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if known.longest >= 2.0 ** 53:
        raise ValueError("components are too large for exact products")
    shards = Shards(known)
    pages = settle(build_pages(vecs, shards), "mtree-pages")
    radii = np.full(shards.count, -np.inf)
    for r in pages.filter("id = -1").select("cell", "data").collect():  # a number for each shard
        radii[r["cell"]] = pickle.loads(bytes(r["data"]))
    shared = spark.sparkContext.broadcast((known, shards, radii))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, own, far_out = shared.value
        owner = np.repeat(np.arange(len(own.blocks)), own.blocks)
        for batch in batches:
            if batch.num_rows:
                q, ids = matrix(batch.column(1)), batch.column(0).to_numpy(zero_copy_only=False)
                least = np.ceil(least_scores(q, ids, seen, k) - 1e-6)
                norm = (q ** 2).sum(axis=1) + own.longest
                far = np.where(np.isfinite(least), np.sqrt(np.maximum(norm - 2 * np.where(np.isfinite(least), least, 0), 0)), np.inf) + 1e-7 * (1 + np.sqrt(norm))
                near = own.apart(q, query=True)[:, owner] - far_out[None, :]
                who, cell = np.nonzero((near <= far[:, None]) & np.isfinite(far_out)[None, :])
                data = [v + b.tobytes() for v, b in zip(batch.column(1).to_pylist(), least, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(ids[who]), pa.array([data[i] for i in who], pa.binary())], ["cell", "id", "data"])

    routed = map_arrow(query_rows(vecs, every), route, "cell long, id long, data binary")

    def load(ids: np.ndarray, datas: list[bytes]) -> Tree:
        return Tree(known.longest, {int(i): pickle.loads(p) for i, p in zip(ids, datas, strict=True) if i >= 0})

    def probe(tree: Tree, ids: np.ndarray, datas: list[bytes]) -> pa.RecordBatch:
        both = matrix(datas)
        found = [tree.search(v[:-1], int(i), k, float(v[-1])) for i, v in zip(ids, both, strict=True)]
        who = np.repeat(ids, [len(f[0]) for f in found])
        return pa.RecordBatch.from_arrays(
            [pa.array(who), pa.array(np.concatenate([f[0] for f in found])), pa.array(np.concatenate([f[1] for f in found]).astype(np.int64))],
            ["query_id", "vec_id", "score"],
        )

    return best(in_cells(pages, routed, deal_queries(known.count // every), load, probe, FOUND), k)


SQL = """
WITH whole AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::double)) AS z
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, v.vec_id, list_inner_product(q.z, v.z)::bigint AS score
  FROM whole q JOIN whole v ON q.vec_id % 20 = 0 AND q.vec_id <> v.vec_id)
SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::integer AS rank, vec_id, score
FROM scored
QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) <= 20
"""
