"""Hash-bucket baseline: random sign hyperplanes or cross polytopes, several tables, multi-probe."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.distance import close_pairs, gathered
from proxigraph.functions.prng import draw_value
from proxigraph.operators import resident
from proxigraph.operators.exact import top_k
from proxigraph.operators.index import SearchResult
from proxigraph.operators.model import PointSet, to_lists, to_matrix
from proxigraph.runtime import discard, map_arrow, settle

#: Members that one task holds of a bucket.
CELL_ROWS = 8192
QUERY_BLOCK = 512
#: Points of one range of ids, about, and the most such ranges: a bound on candidates is found by counts in them.
RANGE_ROWS = 2048
MOST_RANGES = 512


def normals(tables: int, bits: int, dims: int, seed: int = 42) -> np.ndarray:
    """tables x bits x dims of +-1, each a hashed draw."""
    return np.array([[[1.0 if draw_value(seed, t, b, j) & 1 else -1.0 for j in range(dims)] for b in range(bits)] for t in range(tables)])


def projections(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Left-fold dot products of rows x with rows w."""
    out = np.zeros((len(x), len(w)))
    for j in range(x.shape[1]):
        out += x[:, j: j + 1] * w[None, :, j]
    return out


def coded(points: PointSet, tables: int = 8, bits: int = 12, probes: int = 1, kind: str = "sign", seed: int = 42) -> DataFrame:
    """id, vec, codes: each point's bucket in each table, one table after the other, and behind each bucket, for
    queries, the next probes - 1: those reached by flipping the bits (or taking the axes) of least margin."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = None
        for b in batches:
            if not b.num_rows:
                continue
            x = to_matrix(b.column(1))
            w = normals(tables, bits, x.shape[1], seed) if w is None else w
            out = []
            for t in range(tables):
                y = projections(x, w[t])
                if kind == "sign":
                    code = ((y > 0).astype(np.int64) << np.arange(bits)).sum(axis=1)
                    flip = np.argsort(np.abs(y), axis=1, kind="stable")[:, : max(0, probes - 1)]
                    out.append(np.column_stack([code, code[:, None] ^ (np.int64(1) << flip)]))
                else:  # the axis of a rotated space that a point is closest to, with its sign
                    near = np.argsort(-np.abs(y), axis=1, kind="stable")[:, :probes]
                    out.append(near * 2 + (np.take_along_axis(y, near, axis=1) > 0))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), to_lists(np.concatenate(out, axis=1), pa.int64())], ["id", "vec", "codes"])

    return map_arrow(points.plain(), run, "id long, vec array<double>, codes array<bigint>")


def buckets(points: PointSet, tables: int = 8, bits: int = 12, probes: int = 1, kind: str = "sign", seed: int = 42) -> DataFrame:
    """id, vec, tbl, bucket, probe: the rows of `coded`, one a bucket."""
    each = F.floor(F.size("codes") / F.lit(tables)).cast("int")
    rows = coded(points, tables, bits, probes, kind, seed).select("id", "vec", each.alias("m"), F.posexplode("codes").alias("at", "bucket"))
    return rows.select("id", "vec", F.floor(F.col("at") / F.col("m")).cast("int").alias("tbl"), "bucket", (F.col("at") % F.col("m")).alias("probe"))


@dataclass(frozen=True)
class HashIndex:
    """rows: cell, id, vec, codes (a bucket a table), tbl, bucket. A cell of the store holds several buckets, and a
    bucket of more than CELL_ROWS members is dealt to cells of its own by hashed id."""

    rows: DataFrame
    folder: str
    cells: int
    groups: int
    large: dict  # (tbl, bucket) -> (first cell, how many)
    bounds: np.ndarray  # ids that end the ranges, ascending
    points: int
    metric: str
    tables: int
    bits: int = 0
    kind: str = ""
    seed: int = 42

    @classmethod
    def build(cls, points: PointSet, kind: str = "sign", tables: int = 8, bits: int = 12, seed: int = 42) -> HashIndex:
        if bits > 52:
            raise ValueError("a bucket must fit 53 bits")
        return cls.of_codes(coded(points, tables, bits, 1, kind, seed), points.metric, tables, bits, kind, seed)

    @classmethod
    def of_codes(cls, codes: DataFrame, metric: str, tables: int, *made) -> HashIndex:
        """Of id, vec, codes: a bucket a table."""
        spent: list[str] = []
        codes = settle(codes.select("id", "vec", "codes"), "coded", spent)
        n = codes.count()
        ranges = min(MOST_RANGES, max(1, n // RANGE_ROWS))
        bounds = np.unique(np.array(codes.approxQuantile("id", [i / ranges for i in range(1, ranges)], 0.1 / ranges) if ranges > 1 else [], dtype=np.int64))
        each = codes.select("*", F.posexplode("codes").alias("tbl", "bucket"))
        hot = each.groupBy("tbl", "bucket").count().filter(F.col("count") > CELL_ROWS).orderBy("tbl", "bucket").collect()  # at most tables * n / CELL_ROWS
        groups = max(1, -(-n * tables // CELL_ROWS))
        large, cells = {}, groups
        for r in hot:
            large[r["tbl"], r["bucket"]] = cells, -(-r["count"] // CELL_ROWS)
            cells += large[r["tbl"], r["bucket"]][1]
        own = _spans(each, groups, large)
        placed = own.select((F.col("at") + F.pmod(F.xxhash64("id"), "many")).alias("cell"), "id", "vec", "codes", "tbl", "bucket")
        stored = resident.store(placed.repartition("cell").sortWithinPartitions("cell", "id"), "buckets")
        discard(codes.sparkSession, spent)
        return cls(*stored, cells, groups, large, bounds, n, metric, tables, *made)

    def search(self, queries: PointSet, k: int = 10, probes: int = 1, most: int | None = None, spent: list[str] | None = None) -> SearchResult:
        """The k nearest among the members of the probed buckets; `most` bounds the candidates of a
        query (those of the first probes, then the least ids), a parameter of the method. What the search
        settles is added to `spent`, for who discards it once the result is read."""
        return self.search_codes(coded(queries, self.tables, self.bits, probes, self.kind, self.seed), k, probes, most, spent)

    def search_codes(self, queries: DataFrame, k: int = 10, probes: int = 1, most: int | None = None, spent: list[str] | None = None) -> SearchResult:
        """search of id, vec, codes, as `coded` gives them."""
        queries = settle(queries.select("id", "vec", "codes"), "asked", spent)
        each = F.floor(F.size("codes") / F.lit(self.tables))
        asked = queries.select("*", F.posexplode("codes").alias("place", "bucket")).withColumn("tbl", F.floor(F.col("place") / each).cast("int"))
        own = _spans(asked, self.groups, self.large).select(F.explode(F.sequence("at", F.col("at") + F.col("many") - 1)).alias("cell"), "*")
        # a query's buckets, its limit, and the bucket that it visits, travel as more components
        codes, visited = F.transform("codes", lambda c: c.cast("double")), F.array(F.col("tbl").cast("double"), F.col("bucket").cast("double"))
        cut = most is not None and most < self.points
        limit = []
        if cut:
            limits = settle(self._limits(own.select("cell", "id", F.concat(codes, visited).alias("vec")), probes, most), "limits", spent)
            own = own.join(limits.select(F.col("qid").alias("id"), "last"), "id")
            limit = [F.array(F.col("last").cast("double"))]
        routed = own.select("cell", "id", F.concat("vec", codes, *limit, visited).alias("vec"))
        metric, tables, bounds = self.metric, self.tables, self.bounds

        def ask(held, table: pa.Table) -> pa.RecordBatch:
            q_ids, out = table.column("id").to_numpy(), []
            for mine, both, t, members in _visits(held, table):
                if cut:
                    out.append((mine, *_meet_first(both[:, :-1], both[:, -1], t, tables, *members, bounds, metric, k)))
                else:
                    out.append((mine, *_meet(both, t, tables, *members, metric, k)))
            r, i, d, e = (np.concatenate([o[0][o[1]] if j == 1 else o[j] for o in out]) if out else np.empty(0, dtype) for j, dtype in ((1, np.int64), (2, np.int64), (3, float), (4, bool)))
            met = np.zeros(len(q_ids), dtype=np.int64)
            for o in out:
                met[o[0]] += o[5]
            order = np.argsort(r, kind="stable")
            offsets = pa.array(np.concatenate([[0], np.cumsum(np.bincount(r, minlength=len(q_ids)))]).astype(np.int32))
            lists = [pa.ListArray.from_arrays(offsets, pa.array(v[order])) for v in (i, d, e)]
            return pa.RecordBatch.from_arrays([pa.array(q_ids), *lists, pa.array(met)], ["qid", "ids", "dists", "last", "met"])

        met = settle(resident.answer(routed, self.rows, self.folder, ["id", "vec", "codes", "tbl", "bucket"], self.cells, _loader(metric), ask, "qid long, ids array<bigint>, dists array<double>, last array<boolean>, met long"), "candidates", spent)
        found = met.select("qid", F.explode(F.arrays_zip("ids", "dists", "last")).alias("e")).select("qid", F.col("e.ids").alias("id"), F.col("e.dists").alias("dist"), F.col("e.last").alias("last"))
        if cut:  # of its last range of ids, a query takes the first ones
            edge = found.filter("last").join(limits.select("qid", "more"), "qid").withColumn("_n", F.row_number().over(Window.partitionBy("qid").orderBy("id", "dist")))
            found = found.filter("not last").select("qid", "id", "dist").unionByName(edge.filter(F.col("_n") <= F.col("more")).select("qid", "id", "dist"))
        n = F.coalesce("n", F.lit(0).cast("long"))
        n = n if most is None else F.least(n, F.lit(most).cast("long"))
        stats = queries.select(F.col("id").alias("qid")).join(met.groupBy("qid").agg(F.sum("met").alias("n")), "qid", "left").select("qid", F.lit(probes).cast("long").alias("hops"), n.alias("dist_comps"), n.alias("visited"))
        return SearchResult(top_k(found.select("qid", "id", "dist"), k), stats)

    def _limits(self, routed: DataFrame, probes: int, most: int) -> DataFrame:
        """(qid, last long, more long): of each query with candidates the range of ids, counted on from one probe to the
        next, in which its first `most` candidates end, and how many of them lie in it. Cells return only counts."""
        tables, bounds, ranges = self.tables, self.bounds, len(self.bounds) + 1
        size = probes * ranges

        def count(held, table: pa.Table) -> pa.RecordBatch:
            counts = np.zeros((table.num_rows, size), dtype=np.uint32)
            for mine, both, t, (ids, _, codes, usable) in _visits(held, table):
                least, before = _probed(both.reshape(len(both), tables, -1), t, codes, tables)
                key = least.astype(np.int64) * ranges + np.searchsorted(bounds, ids)
                r, c = np.nonzero(~before & usable)
                counts[mine] += np.bincount(r * size + key[r, c], minlength=len(mine) * size).reshape(-1, size).astype(np.uint32)
            some = np.flatnonzero(counts.any(axis=1))
            packed = [row.astype(np.uint16 if row.max() < 1 << 16 else np.uint32).tobytes() for row in counts[some]]
            return pa.RecordBatch.from_arrays([pa.array(table.column("id").to_numpy()[some]), pa.array(packed, pa.binary())], ["qid", "counts"])

        def end(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            now, total, done = None, None, []

            def limit() -> tuple[int, int, int]:
                sums = np.cumsum(total)
                last = int(np.searchsorted(sums, most))
                return now, last, most - int(sums[last - 1]) if 0 < last < size else most

            for batch in batches:
                for qid, packed in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    raw = packed.as_buffer()
                    if qid != now:
                        if now is not None:
                            done.append(limit())
                        now, total = qid, np.zeros(size, dtype=np.int64)
                    total += np.frombuffer(raw, np.uint16 if raw.size == 2 * size else np.uint32)
                yield pa.RecordBatch.from_arrays([pa.array([x[j] for x in done], pa.int64()) for j in range(3)], ["qid", "last", "more"])
                done.clear()
            if now is not None:
                yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in limit()], ["qid", "last", "more"])

        counted = resident.answer(routed, self.rows, self.folder, ["id", "vec", "codes", "tbl", "bucket"], self.cells, _loader(self.metric), count, "qid long, counts binary")
        return map_arrow(counted.repartition("qid").sortWithinPartitions("qid"), end, "qid long, last long, more long")


def _loader(metric: str):
    """(tbl, bucket) -> ids, vectors, buckets of the members in all tables, and whether they can have a distance."""

    def load(table: pa.Table):
        tbl, bucket = (table.column(c).to_numpy() for c in ("tbl", "bucket"))
        order = np.lexsort((table.column("id").to_numpy(), bucket, tbl))
        table, tbl, bucket = table.take(pa.array(order)), tbl[order], bucket[order]
        first = np.flatnonzero((np.diff(tbl, prepend=-1) != 0) | (np.diff(bucket, prepend=bucket[:1] - 1) != 0))
        ids, x, codes = table.column("id").to_numpy(), to_matrix(table.column("vec")), to_matrix(table.column("codes"))
        usable = np.isfinite(x).all(axis=1) & (x.any(axis=1) if metric == "cosine" else True)
        return {(int(tbl[a]), int(bucket[a])): (ids[a:b], x[a:b], codes[a:b], usable[a:b]) for a, b in zip(first, [*first[1:], len(ids)], strict=True)}

    return load


def _visits(held, table: pa.Table) -> Iterator[tuple]:
    """Blocks of the queries that visit one bucket of a cell: their rows, their components without the bucket (the last
    two), its table, its members."""
    both = to_matrix(table.column("vec"))
    names, back = np.unique(both[:, -2:], axis=0, return_inverse=True)
    for at, (t, bucket) in enumerate(names.astype(np.int64).tolist()):
        if (t, bucket) in held:
            who = np.flatnonzero(back.reshape(-1) == at)
            for lo in range(0, len(who), QUERY_BLOCK):
                mine = who[lo: lo + QUERY_BLOCK]
                yield mine, both[mine, :-2], t, held[t, bucket]


def _spans(rows: DataFrame, groups: int, large: dict) -> DataFrame:
    """rows (tbl, bucket, ...) with at, many: the cells of the bucket."""
    spark = rows.sparkSession
    hot = spark.createDataFrame([(int(t), int(b), int(a), int(m)) for (t, b), (a, m) in large.items()], "tbl int, bucket long, _at long, many long")
    met = rows.join(F.broadcast(hot), ["tbl", "bucket"], "left")
    return met.withColumn("at", F.coalesce("_at", F.pmod(F.xxhash64("tbl", "bucket"), F.lit(groups).cast("long")))).withColumn("many", F.coalesce("many", F.lit(1).cast("long"))).drop("_at")


def _probed(asked: np.ndarray, t: int, codes: np.ndarray, upto: int) -> tuple[np.ndarray, np.ndarray]:
    """Of queries (their buckets by table and probe) and members of one bucket of table t: the least probe by which they
    meet in the tables below `upto`, and whether they meet in one before t."""
    least = np.full((len(asked), len(codes)), asked.shape[2], dtype=np.int16)
    before = np.zeros(least.shape, dtype=bool)
    for other in range(upto):
        for p in range(asked.shape[2]):
            same = asked[:, other, p][:, None] == codes[None, :, other]
            if other < t:
                before |= same
            np.minimum(least, p, out=least, where=same)
    return least, before


def _nearest(q: np.ndarray, x: np.ndarray, ids: np.ndarray, usable: np.ndarray, metric: str, k: int, skip: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row of the query, id, distance of the k nearest usable members of each, without the pairs to skip."""
    ids = ids[usable]
    r, c, d = close_pairs(q, x[usable], metric, k, skip=skip[:, usable])
    order = np.lexsort((ids[c], d, r))
    r, c, d = r[order], c[order], d[order]
    keep = np.arange(len(r)) - np.searchsorted(r, r, side="left") < k
    return r[keep], ids[c[keep]], d[keep]


def _meet(both: np.ndarray, t: int, tables: int, ids: np.ndarray, x: np.ndarray, codes: np.ndarray, usable: np.ndarray, metric: str, k: int):
    """Of queries (vectors, then their buckets in every table) and the members of one bucket of table t, without the
    pairs that meet in an earlier table: row of the query, id, distance of the k nearest, and that they are not of a last
    range; and how many members each query meets."""
    q, asked = both[:, : x.shape[1]], both[:, x.shape[1]:].reshape(len(both), tables, -1)
    _, before = _probed(asked, t, codes, t)
    r, i, d = _nearest(q, x, ids, usable, metric, k, before)
    return r, i, d, np.zeros(len(r), dtype=bool), len(x) - before.sum(axis=1)


def _meet_first(both: np.ndarray, last: np.ndarray, t: int, tables: int, ids: np.ndarray, x: np.ndarray, codes: np.ndarray, usable: np.ndarray, bounds: np.ndarray, metric: str, k: int):
    """_meet of the members in the ranges (by the least probe of any table, then the id) below a query's last one, and
    all of the last one itself, marked."""
    q, asked = both[:, : x.shape[1]], both[:, x.shape[1]:].reshape(len(both), tables, -1)
    least, before = _probed(asked, t, codes, tables)
    place = least.astype(np.int64) * (len(bounds) + 1) + np.searchsorted(bounds, ids)
    met = len(x) - before.sum(axis=1)
    near = _nearest(q, x, ids, usable, metric, k, before | (place >= last[:, None]))
    r, c = np.nonzero(~before & usable & (place == last[:, None]))
    d = gathered(q.T, r, x.T, c, metric)
    finite = np.isfinite(d)
    edge = r[finite], ids[c[finite]], d[finite]
    return *(np.concatenate(z) for z in zip(near, edge, strict=True)), np.repeat([False, True], [len(near[0]), finite.sum()]), met


def library_lsh(points: PointSet, queries: PointSet, k: int, bucket_length: float = 2.0, tables: int = 4, seed: int = 42) -> DataFrame:
    """Spark's own bucketed random projections, as a further comparison: qid, id, dist, rank. Its model gives the
    buckets; pairs that share one meet as in HashIndex, as its own join makes a row of every such pair."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array

    p = points.plain().select("id", "vec", array_to_vector("vec").alias("x"))
    q = queries.plain().select("id", "vec", array_to_vector("vec").alias("x"))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", bucketLength=bucket_length, numHashTables=tables, seed=seed).fit(p)
    codes = F.array(*[vector_to_array(F.col("h")[t])[0].cast("long") for t in range(tables)]).alias("codes")
    made = HashIndex.of_codes(model.transform(p).select("id", "vec", codes), points.metric, tables)
    return made.search_codes(model.transform(q).select("id", "vec", codes), k).results
