"""Graphs as edge tables (src, dst, dist): the shared tools, as DataFrame plans."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.functions.distance import expression, gathered
from proxigraph.functions.prng import draw
from proxigraph.operators.kernels import prune
from proxigraph.operators.model import PointSet, to_matrix
from proxigraph.runtime import map_arrow, settle, ship

#: Points that a task holds on either side of the pairs it measures, and below which a block is not cut for idle cores.
PAIR_BLOCK, LEAST_BLOCK = 8192, 1024


def semisort(edges: DataFrame, key: str, value: str = "src") -> DataFrame:
    """Equal keys together: key and the sorted array of the values, one hash exchange, no total order."""
    return edges.groupBy(key).agg(F.array_sort(F.collect_list(value)).alias("members"))


def undirect(edges: DataFrame) -> DataFrame:
    """Every edge and its opposite, once."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")
    return edges.select("src", "dst", "dist").unionByName(back).dropDuplicates(["src", "dst"])


def cap_degree(edges: DataFrame, cap: int, seed: int = 42, rnd: int = 0) -> DataFrame:
    """At most `cap` edges of each source, those with the least draws."""
    order = Window.partitionBy("src").orderBy(draw(seed, rnd, "src", "dst"), "dst")
    return edges.withColumn("_n", F.row_number().over(order)).filter(F.col("_n") <= cap).drop("_n")


def nearest(edges: DataFrame, k: int) -> DataFrame:
    """The k nearest targets of every source, by (dist, dst)."""
    order = Window.partitionBy("src").orderBy("dist", "dst")
    return edges.withColumn("_n", F.row_number().over(order)).filter(F.col("_n") <= k).drop("_n")


def with_distance(pairs: DataFrame, points: PointSet) -> DataFrame:
    """src, dst, dist of (src, dst)."""
    p = points.plain()
    a = p.select(F.col("id").alias("src"), F.col("vec").alias("a"))
    b = p.select(F.col("id").alias("dst"), F.col("vec").alias("b"))
    return pairs.join(a, "src").join(b, "dst").select("src", "dst", expression(points.metric, "a", "b").alias("dist"))


def nearest_pairs(pairs: DataFrame, points: PointSet, k: int) -> DataFrame:
    """src, dst, dist: the k nearest targets of every source among pairs (src, dst), which may repeat. Points
    are dealt to blocks by hashed id; a group is the pairs between two blocks with the vectors of both, so a
    vector travels once a group and not once a pair, and k answers a source leave it."""
    p = points.plain()
    metric = points.metric
    n, cores = p.count(), p.sparkSession.sparkContext.defaultParallelism
    many = max(1, -(-n // PAIR_BLOCK), min(2 * math.ceil(math.sqrt(cores)), -(-n // LEAST_BLOCK)))
    ship(p.sparkSession)

    def own(c: str):
        return F.pmod(F.xxhash64(c), F.lit(many).cast("long"))

    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(many - 1).cast("long")))
    met = pairs.select(own("src").alias("i"), own("dst").alias("j"), F.lit(0).alias("side"), "src", "dst", F.lit(None).cast("array<double>").alias("vec"))
    for side, i, j in ((1, own("id"), every), (2, every, own("id"))):
        met = met.unionByName(p.select(i.alias("i"), j.alias("j"), F.lit(side).alias("side"), F.col("id").alias("src"), F.col("id").alias("dst"), "vec"))

    def one(table: pa.Table) -> pa.Table:
        side = table.column("side").to_numpy()
        left, right = (table.filter(pa.array(side == s)).sort_by("src").combine_chunks() for s in (1, 2))
        asked = table.filter(pa.array(side == 0))
        a, b = left.column("src").to_numpy(), right.column("src").to_numpy()
        src, dst = asked.column("src").to_numpy(), asked.column("dst").to_numpy()
        there = np.isin(src, a) & np.isin(dst, b)
        r, c = np.divmod(np.unique(np.searchsorted(a, src[there]) * max(1, len(b)) + np.searchsorted(b, dst[there])), max(1, len(b)))
        d = gathered(to_matrix(left.column("vec")).T, r, to_matrix(right.column("vec")).T, c, metric) if len(r) else np.empty(0)
        order = np.lexsort((c, d, r))
        r, c, d = r[order], c[order], d[order]
        keep = np.arange(len(r)) - np.searchsorted(r, r, side="left") < k
        return pa.table({"src": pa.array(a[r[keep]], pa.int64()), "dst": pa.array(b[c[keep]], pa.int64()), "dist": pa.array(d[keep], pa.float64())})

    return nearest(met.groupBy("i", "j").applyInArrow(one, "src long, dst long, dist double"), k)


def alpha_prune(edges: DataFrame, points: PointSet, degree: int, alpha: float = 1.2, keep_pruned: bool = False) -> DataFrame:
    """Each source's edges pruned to `degree` by the alpha rule. The vectors of the candidates ride
    with the edges, so a source's candidates, at most its degree, meet in one place."""
    p = points.plain().select(F.col("id").alias("dst"), "vec")
    metric = points.metric
    lists = edges.join(p, "dst").groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst", "vec"))).alias("c"))
    flat = lists.select("src", F.col("c.dst").alias("dst"), F.col("c.dist").alias("dist"), F.col("c.vec").alias("vec"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            src = batch.column(0).to_numpy()
            size = np.diff(batch.column(1).offsets.to_numpy())
            dst, dist = (batch.column(i).flatten().to_numpy() for i in (1, 2))
            vecs = to_matrix(batch.column(3).flatten()).T
            row = np.repeat(np.arange(len(src)), size)
            col = np.arange(len(dst)) - np.repeat(np.cumsum(size) - size, size)
            cand, far = np.full((len(src), max(1, int(size.max()))), -1, dtype=np.int64), np.full((len(src), max(1, int(size.max()))), np.inf)
            # candidates are named by their place in the batch; a list is in the order of (dist, dst)
            cand[row, col], far[row, col] = np.where(dst == src[row], -1, np.arange(len(dst))), dist
            got, d = prune(vecs, np.full(len(src), -2), cand, far, degree, alpha, "alpha", metric, keep_pruned)
            r, c = np.nonzero(got >= 0)
            yield pa.RecordBatch.from_arrays([pa.array(src[r]), pa.array(dst[got[r, c]]), pa.array(d[r, c])], ["src", "dst", "dist"])

    return map_arrow(flat, run, "src long, dst long, dist double", 256)


def merge_reverse(graph: DataFrame, new_edges: DataFrame, points: PointSet, degree: int, alpha: float = 1.2) -> DataFrame:
    """graph with the new edges' opposites: they are grouped by the existing endpoint and joined to its
    list; only lists beyond `degree` are pruned again."""
    arrivals = new_edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")
    both = graph.select("src", "dst", "dist").unionByName(arrivals).dropDuplicates(["src", "dst"])
    both = both.withColumn("_n", F.count("*").over(Window.partitionBy("src")))
    full = both.filter(F.col("_n") > degree).drop("_n")
    return both.filter(F.col("_n") <= degree).drop("_n").unionByName(alpha_prune(full, points, degree, alpha))


def pack(edges: DataFrame, degree: int) -> DataFrame:
    """id, nbrs: lists of fixed length by (dist, dst), padded with -1."""
    lists = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst"))).alias("c"))
    ids = F.slice(F.col("c.dst"), 1, degree)
    return lists.select(F.col("src").alias("id"), F.concat(ids, F.array_repeat(F.lit(-1).cast("long"), F.lit(degree) - F.size(ids))).alias("nbrs"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select(F.col("id").alias("src"), F.posexplode("nbrs").alias("place", "dst")).filter("dst >= 0")


def union_local(*graphs: DataFrame) -> DataFrame:
    """The distinct edges of several graphs."""
    out = graphs[0].select("src", "dst", "dist")
    for g in graphs[1:]:
        out = out.unionByName(g.select("src", "dst", "dist"))
    return out.dropDuplicates(["src", "dst"])


def two_hop(edges: DataFrame) -> DataFrame:
    """(src, dst): targets of targets and targets, without the source itself."""
    one = edges.select("src", "dst")
    far = one.alias("a").join(one.alias("b"), F.col("a.dst") == F.col("b.src")).select(F.col("a.src").alias("src"), F.col("b.dst").alias("dst"))
    return far.unionByName(one).filter("src <> dst").distinct()


def descent_round(
    edges: DataFrame, points: PointSet, k: int, cap: int | None = 2000, seed: int = 42, rnd: int = 0, blocks: int = 1, known: DataFrame | None = None,
) -> DataFrame:
    """One round of neighbour descent: add opposites, cap degrees, and keep each source's k closest
    among its neighbours, capped neighbours and their neighbours. Sources are handled in `blocks`
    written one by one, to bound what lies on disk at once; the result does not depend on it.
    known: the edges of the round before, if no cap cut it and none cuts this one: two-hop ways of them were
    looked at then and are left out now, which changes nothing."""
    both = undirect(edges)
    if cap is not None:
        both = cap_degree(both, cap, seed, rnd)
    both = both.select("src", "dst")
    if known is None:
        both = both.withColumn("fresh", F.lit(True))
    else:
        met = undirect(known).select("src", "dst", F.lit(False).alias("fresh"))
        both = both.join(met, ["src", "dst"], "left").withColumn("fresh", F.coalesce("fresh", F.lit(True)))
    both = settle(both, "descent-edges")
    out = None
    for b in range(blocks):
        mine = both.filter(F.pmod(F.xxhash64("src"), F.lit(blocks)) == b) if blocks > 1 else both
        way = (F.col("a.dst") == F.col("b.src")) & (F.col("a.fresh") | F.col("b.fresh"))
        far = mine.alias("a").join(both.alias("b"), way).select(F.col("a.src").alias("src"), F.col("b.dst").alias("dst"))
        own = edges.select("src", "dst")
        own = own.filter(F.pmod(F.xxhash64("src"), F.lit(blocks)) == b) if blocks > 1 else own
        pairs = far.unionByName(mine.select("src", "dst")).unionByName(own).filter("src <> dst")
        part = nearest_pairs(pairs, points, k)
        part = settle(part, "descent-block") if blocks > 1 else part
        out = part if out is None else out.unionByName(part)
    return out


def changed(before: DataFrame, after: DataFrame) -> DataFrame:
    """Edges of after that are not in before."""
    return after.join(before.select("src", "dst"), ["src", "dst"], "left_anti")


def reachable(edges: DataFrame, start: int) -> DataFrame:
    """id, hops: the vertices that can be reached from start, breadth first, a settled join a round; as
    many rounds as it takes. What is seen is settled now and then, so that the plan stays short."""
    spark = edges.sparkSession
    links = settle(edges.select("src", "dst").distinct(), "links")
    seen = spark.createDataFrame([(start, 0)], "id long, hops int")
    front, hop = seen, 0
    while not front.isEmpty():
        hop += 1
        step = front.join(links, front["id"] == links["src"]).select(F.col("dst").alias("id")).distinct()
        front = settle(step.join(seen, "id", "left_anti").withColumn("hops", F.lit(hop)), "front")
        seen = seen.unionByName(front)
        if hop % 8 == 0:
            seen = settle(seen, "seen")
    return seen


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row: vertices with edges, edges, least, mean and most out-degree, mean edge length."""
    degrees = edges.groupBy("src").agg(F.count("*").alias("deg"), F.sum(F.round(F.col("dist") * (1 << 20)).cast("decimal(38,0)")).alias("len"))
    return degrees.agg(
        F.count("*").alias("vertices"), F.sum("deg").alias("edges"), F.min("deg").alias("least"), F.max("deg").alias("most"),
        F.round(F.sum("deg") / F.count("*"), 6).alias("mean_degree"),
        F.round(F.sum("len").cast("double") / (1 << 20) / F.sum("deg"), 6).alias("mean_length"),
    )


def fingerprint(edges: DataFrame) -> DataFrame:
    """One row that tells edge sets apart, whatever the order and the layout of the rows."""
    return edges.agg(F.expr("bit_xor(xxhash64(src, dst))").alias("print"), F.count("*").alias("edges"))

