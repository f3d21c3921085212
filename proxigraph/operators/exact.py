"""Exact answers: k nearest, range, count and box searches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.distance import block, close_pairs
from proxigraph.operators.model import PointSet, to_matrix
from proxigraph.runtime import map_arrow, settle

#: Queries are sent to all executors up to this size, else dealt out in blocks.
BROADCAST_BYTES = 64 << 20
QUERY_BLOCK, POINT_BLOCK = 512, 4096
BLOCK_ROWS = 65_536
#: Points of a bin that one task holds.
BIN_ROWS = 16_384
FOUND = "qid long, id long, dist double"


def nearest_of(q_ids, q, ids, x, metric: str, k: int | None, radius: float | None = None, exclude_self: bool = False):
    """(query index, id, distance) of the k nearest, or of all within radius, of rows x."""
    parts = []
    for a in range(0, len(q), QUERY_BLOCK):
        best: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        for b in range(0, len(x), POINT_BLOCK):
            own = q_ids[a: a + QUERY_BLOCK, None] == ids[None, b: b + POINT_BLOCK] if exclude_self else None
            r, c, d = close_pairs(q[a: a + QUERY_BLOCK], x[b: b + POINT_BLOCK], metric, k, radius, own)
            best.append((r + a, ids[b + c], d))
        r, i, d = (np.concatenate([x[j] for x in best]) for j in range(3)) if best else (np.empty(0, np.int64),) * 2 + (np.empty(0),)
        if radius is None and len(r):
            order = np.lexsort((i, d, r))
            r, i, d = r[order], i[order], d[order]
            keep = np.arange(len(r)) - np.searchsorted(r, r, side="left") < k
            r, i, d = r[keep], i[keep], d[keep]
        parts.append((r, i, d))
    return tuple(np.concatenate([p[j] for p in parts]) for j in range(3))


def _scan(base: PointSet, queries: PointSet, metric: str, k: int | None, radius: float | None, exclude_self: bool) -> DataFrame:
    """Candidates of every query. Few queries are broadcast after their size is checked, and each task
    answers them over its rows; more are dealt out in blocks against blocks of rows."""
    spark = base.df.sparkSession
    q = queries.plain()
    first = q.filter("vec is not null").select(F.size("vec").alias("d")).first()
    if first is None:
        return spark.createDataFrame([], FOUND)
    n_q = q.count()

    if n_q * first["d"] * 8 <= BROADCAST_BYTES:
        table = q.toArrow()
        shared = spark.sparkContext.broadcast((table.column("id").to_numpy(), to_matrix(table.column("vec"))))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            q_ids, qs = shared.value
            held: list[pa.RecordBatch] = []

            def flush() -> Iterator[pa.RecordBatch]:
                whole = pa.Table.from_batches(held)
                r, i, d = nearest_of(q_ids, qs, whole.column(0).to_numpy(), to_matrix(whole.column(1)), metric, k, radius, exclude_self)
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[r]), pa.array(i), pa.array(d)], ["qid", "id", "dist"])

            rows = 0
            for batch in batches:
                if batch.num_rows:
                    held.append(batch)
                    rows += batch.num_rows
                if rows >= BLOCK_ROWS:
                    yield from flush()
                    held, rows = [], 0
            if held:
                yield from flush()

        return map_arrow(base.plain().filter("vec is not null"), run, FOUND)

    blocks = max(1, -(-base.df.count() // BLOCK_ROWS))
    left = base.plain().select(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("cell"), F.lit(0).alias("kind"), "id", "vec")
    right = q.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("cell"), F.lit(1).alias("kind"), "id", "vec")
    both = left.unionByName(right).filter("vec is not null").repartition("cell").sortWithinPartitions("cell", "kind")

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for is_query, table, held in stream_cells(batches):
            if is_query:
                q_ids = table.column("id").to_numpy()
                r, i, d = nearest_of(q_ids, to_matrix(table.column("vec")), held.column("id").to_numpy(), to_matrix(held.column("vec")), metric, k, radius, exclude_self)
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[r]), pa.array(i), pa.array(d)], ["qid", "id", "dist"])

    return map_arrow(both, pair, FOUND)


def stream_cells(batches: Iterator[pa.RecordBatch]):
    """Of rows sorted by (cell, kind), with kind 0 the bounded rows of a cell and kind 1 its queries:
    yields (True, queries, the cell's rows) per batch of queries. Only one cell is held at a time."""
    now, held, whole = None, [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        cell, kind = batch.column("cell").to_numpy(zero_copy_only=False), batch.column("kind").to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero((np.diff(cell) != 0) | (np.diff(kind) != 0)) + 1).tolist(), len(cell)]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if cell[a] != now:
                now, held, whole = cell[a], [], None
            part = pa.Table.from_batches([batch.slice(a, b - a)])
            if kind[a] == 0:
                held.append(part)
            elif held:
                whole = pa.concat_tables(held).combine_chunks() if whole is None else whole
                yield True, part, whole


def every_pair(q_ids, q, ids, x, metric: str) -> Iterator[pa.RecordBatch]:
    """qid, id, dist of all pairs, BLOCK_ROWS of them at once."""
    wide = max(1, BLOCK_ROWS // max(1, len(x)))
    for a in range(0, len(q), wide):
        d = block(q[a: a + wide], x, metric)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(q_ids[a: a + wide], len(x))), pa.array(np.tile(ids, len(d))), pa.array(d.ravel())], ["qid", "id", "dist"])


def all_pairs(base: PointSet, queries: PointSet) -> DataFrame:
    """qid, id, dist of every query with every point, for vectors of one length without null components.
    Few queries are broadcast after their size is checked; more are dealt out against blocks of points."""
    metric, q = base.metric, queries.plain()
    spark = q.sparkSession
    size = q.agg(F.sum(F.size("vec")).alias("n")).first()["n"] or 0
    if size * 8 <= BROADCAST_BYTES:
        table = q.toArrow()
        shared = spark.sparkContext.broadcast((table.column("id").to_numpy(), to_matrix(table.column("vec"))))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield from every_pair(*shared.value, batch.column(0).to_numpy(), to_matrix(batch.column(1)), metric)

        return map_arrow(base.plain(), run, FOUND)

    blocks = max(1, -(-base.df.count() // BIN_ROWS))
    left = base.plain().select(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("cell"), F.lit(0).alias("kind"), "id", "vec")
    right = q.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("cell"), F.lit(1).alias("kind"), "id", "vec")
    both = left.unionByName(right).repartition("cell").sortWithinPartitions("cell", "kind")

    def pair(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, table, held in stream_cells(batches):
            yield from every_pair(table.column("id").to_numpy(), to_matrix(table.column("vec")), held.column("id").to_numpy(), to_matrix(held.column("vec")), metric)

    return map_arrow(both, pair, FOUND)


def top_k(found: DataFrame, k: int) -> DataFrame:
    """qid, id, dist, rank: the k smallest (dist, id) of each query."""
    order = Window.partitionBy("qid").orderBy("dist", "id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def exact_knn(base: PointSet, queries: PointSet, k: int = 10, exclude_self: bool = False) -> DataFrame:
    """qid, id, dist, rank: the k nearest points of every query, ties to the smaller id; fewer points
    than k are all returned."""
    return top_k(_scan(base, queries, base.metric, k, None, exclude_self), k)


def exact_range(base: PointSet, queries: PointSet, radius: float, exclude_self: bool = False) -> DataFrame:
    """qid, id, dist of all points within radius."""
    return _scan(base, queries, base.metric, None, radius, exclude_self)


def range_count(base: PointSet, queries: PointSet, radius: float) -> DataFrame:
    """qid, n: how many points are within radius, zeros included."""
    counts = exact_range(base, queries, radius).groupBy("qid").agg(F.count("*").alias("n"))
    return queries.plain().select(F.col("id").alias("qid")).join(counts, "qid", "left").select("qid", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def box_search(points: PointSet, low: list[float], high: list[float]) -> DataFrame:
    """id of the points inside an axis-aligned box, bounds included."""
    inside = F.lit(True)
    for j, (a, b) in enumerate(zip(low, high, strict=True)):
        inside = inside & F.col("vec")[j].between(a, b)
    return points.plain().filter(inside).select("id")


def exact_knn_graph(points: PointSet, k: int) -> DataFrame:
    """src, dst, dist: edges from every point to its k nearest others."""
    found = exact_knn(points, points, k, exclude_self=True)
    return found.select(F.col("qid").alias("src"), F.col("id").alias("dst"), "dist")


def range_self_join(points: PointSet, radius: float) -> DataFrame:
    """u, v, dist: all pairs of points within radius by l2, no pair of rows expanded: copies of a vector are
    one class, named by the smallest id, and pairs are those of classes (u < v); every other member v comes
    once with its class u, at distance 0.

    The norms of points within radius differ by at most radius, so points lie in cells by bands of the
    norm, cut to bounded blocks, and each is compared with its own band and the next one only.
    """
    from proxigraph.functions.distance import norm
    from proxigraph.operators import resident

    if points.metric != "l2" or radius <= 0:
        raise ValueError("bands of norms need l2 and a radius above 0")
    spark = points.df.sparkSession
    p = settle(points.plain().filter("vec is not null"), "join-points")
    reps = p.groupBy("vec").agg(F.min("id").alias("id"))
    banded = settle(reps.select("id", "vec", F.floor(norm("vec") / radius).alias("band")), "join-bands")
    counts = {r["band"]: r["count"] for r in banded.groupBy("band").count().collect()}  # a row a band
    first, cells = {}, 0
    for band in sorted(counts):
        first[band] = cells
        cells += max(1, -(-counts[band] // BLOCK_ROWS))
    spans = spark.createDataFrame([(b, c, max(1, -(-counts[b] // BLOCK_ROWS))) for b, c in first.items()], "b long, at long, many long")
    spans = F.broadcast(spans) if len(first) <= 100_000 else spans
    placed = banded.join(spans, F.col("band") == F.col("b")).select((F.col("at") + F.pmod(F.xxhash64("id"), "many")).alias("cell"), "id", "vec", "band")
    rows, folder = resident.store(placed.repartition("cell"), "join-cells")
    asked = banded.withColumn("to", F.explode(F.array("band", F.col("band") + 1))).join(spans, F.col("to") == F.col("b"))
    # a query's own band travels as one more component
    routed = asked.select(F.explode(F.sequence(F.col("at"), F.col("at") + F.col("many") - 1)).alias("cell"), "id", F.concat("vec", F.array(F.col("band").cast("double"))).alias("vec"))

    def load(table: pa.Table):
        return table.column("id").to_numpy(), to_matrix(table.column("vec")), table.column("band").to_numpy()

    def ask(held, table: pa.Table) -> pa.RecordBatch:
        ids, x, bands = held
        q_ids, both = table.column("id").to_numpy(), to_matrix(table.column("vec"))
        out = []
        for lo in range(0, len(x), POINT_BLOCK):
            r, c, d = close_pairs(both[:, :-1], x[lo: lo + POINT_BLOCK], "l2", radius=radius)
            c = c + lo
            once = (q_ids[r] < ids[c]) | (bands[c] != both[r, -1])
            out.append((q_ids[r[once]], ids[c[once]], d[once]))
        a, b, d = (np.concatenate([o[j] for o in out]) for j in range(3))
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(d)], ["u", "v", "dist"])

    near = resident.answer(routed, rows, folder, ["id", "vec", "band"], max(1, cells), load, ask, "u long, v long, dist double")
    members = p.join(reps.select("vec", F.col("id").alias("u")), "vec").filter("id <> u").select("u", F.col("id").alias("v"), F.lit(0.0).alias("dist"))
    return near.unionByName(members)


def range_by_pivot(base: PointSet, queries: PointSet, pivot: DataFrame, radius: float) -> DataFrame:
    """qid, id, dist of all pairs within radius by l2: by the triangle inequality, partners lie in the same bin of
    the distance to the pivot (one row: o) or in the next ones. Bins are cut to bounded blocks of points, which
    stay where they are; the queries go to the blocks of their bins."""
    from proxigraph.functions.distance import l2
    from proxigraph.operators import resident

    if base.metric != "l2" or radius <= 0:
        raise ValueError("bins need l2 and a radius above 0")
    spark = base.df.sparkSession
    pivot = F.broadcast(pivot)
    binned = settle(base.plain().filter("vec is not null").join(pivot).select("id", "vec", F.floor(l2("vec", "o") / radius).alias("bin")), "bins")
    first, cells = {}, 0
    for r in binned.groupBy("bin").count().orderBy("bin").collect():  # a row a bin
        first[r["bin"]] = (cells, -(-r["count"] // BIN_ROWS))
        cells += first[r["bin"]][1]
    if not cells:
        return spark.createDataFrame([], FOUND)
    spans = spark.createDataFrame([(b, a, m) for b, (a, m) in first.items()], "bin long, at long, many long")
    spans = F.broadcast(spans) if len(first) <= 100_000 else spans
    placed = binned.join(spans, "bin").select((F.col("at") + F.pmod(F.xxhash64("id"), "many")).alias("cell"), "id", "vec")
    rows, folder = resident.store(placed.repartition("cell").sortWithinPartitions("cell", "id"), "bin-cells")
    asked = queries.plain().filter("vec is not null").join(pivot).withColumn("b", F.floor(l2("vec", "o") / radius))
    asked = asked.withColumn("bin", F.explode(F.array(F.col("b") - 1, F.col("b"), F.col("b") + 1))).join(spans, "bin")
    routed = asked.select(F.explode(F.sequence(F.col("at"), F.col("at") + F.col("many") - 1)).alias("cell"), "id", "vec")

    def load(table: pa.Table):
        return table.column("id").to_numpy(), to_matrix(table.column("vec"))

    def ask(held, table: pa.Table) -> pa.RecordBatch:
        q_ids = table.column("id").to_numpy()
        r, i, d = nearest_of(q_ids, to_matrix(table.column("vec")), *held, "l2", None, radius)
        return pa.RecordBatch.from_arrays([pa.array(q_ids[r]), pa.array(i), pa.array(d)], ["qid", "id", "dist"])

    return resident.answer(routed, rows, folder, ["id", "vec"], cells, load, ask, FOUND)


def medoid(points: PointSet) -> DataFrame:
    """id, dist of the point closest to the mean vector; the mean is summed in fixed point, so it does
    not depend on the order of rows."""
    from proxigraph.functions.distance import expression

    cells = points.plain().select(F.posexplode("vec").alias("j", "x"))
    mean = cells.groupBy("j").agg(F.sum(F.round(F.col("x") * (1 << 20)).cast("decimal(38,0)")).alias("s"), F.count("*").alias("n"))
    mean = mean.select("j", (F.col("s").cast("double") / (1 << 20) / F.col("n")).alias("x"))
    mean = mean.agg(F.array_sort(F.collect_list(F.struct("j", "x"))).alias("m")).select(F.transform("m", lambda s: s["x"]).alias("m"))
    d = points.plain().join(F.broadcast(mean)).select("id", expression(points.metric, "vec", "m").alias("dist"))
    return d.orderBy("dist", "id").limit(1)


__all__ = ["all_pairs", "box_search", "exact_knn", "exact_knn_graph", "exact_range", "medoid", "nearest_of", "range_by_pivot", "range_count", "settle", "stream_cells", "top_k"]
