"""The join-round engine: beam search and batch insertion over a graph that no task holds whole.

The state of a search is a table with one row per query: its beam and what it has processed. A round
picks every live query's closest unprocessed beam member, joins these with the adjacency and the
vectors (equi-joins of the frontier only), and merges the new candidates into the beams. It follows
the same rules as the kernel and gives the same answers and counts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.functions.distance import expression
from proxigraph.operators.edges import alpha_prune, merge_reverse
from proxigraph.operators.exact import top_k
from proxigraph.operators.index import SearchResult
from proxigraph.operators.kernels import schedule
from proxigraph.operators.model import PointSet
from proxigraph.runtime import settle

BEAM = "array<struct<dist:double,id:bigint,done:boolean>>"


def beam_rounds(edges: DataFrame, points: PointSet, queries: PointSet, width: int, start: int, k: int = 1, eps: float | None = None) -> DataFrame:
    """qid, qvec, beam, log (array of dist, id in order of processing), comps: the final states."""
    p = points.plain()
    metric = points.metric
    lists = settle(edges.groupBy("src").agg(F.collect_list("dst").alias("nbrs")), "adjacency")
    vecs = settle(p.select(F.col("id").alias("dst"), F.col("vec").alias("x")), "vectors")
    first = p.filter(F.col("id") == start).select(F.col("vec").alias("s"))
    state = queries.plain().join(F.broadcast(first)).select(
        F.col("id").alias("qid"), F.col("vec").alias("qvec"),
        F.array(F.struct(expression(metric, "s", "vec").alias("dist"), F.lit(start).cast("long").alias("id"), F.lit(False).alias("done"))).cast(BEAM).alias("beam"),
        F.array().cast("array<struct<dist:double,id:bigint>>").alias("log"), F.lit(1).cast("long").alias("comps"), F.lit(True).alias("live"),
    )
    state = settle(state, "beam")
    while True:  # every round processes a vertex of each live query, so it ends
        pick = F.filter("beam", lambda e: ~e["done"])[0]
        live = F.col("live") & F.get(F.filter("beam", lambda e: ~e["done"]), F.lit(0)).isNotNull()
        if eps is not None:
            kth = F.get("beam", F.lit(k - 1))["dist"]
            live = live & (kth.isNull() | (F.get(F.filter("beam", lambda e: ~e["done"]), F.lit(0))["dist"] <= (1 + eps) * kth))
        state = state.withColumn("live", live)
        open_ = state.filter("live")
        if open_.isEmpty():
            break
        open_ = open_.withColumn("p", pick)
        moved = open_.select(
            "qid", "qvec", F.transform("beam", lambda e: F.struct(e["dist"].alias("dist"), e["id"].alias("id"), (e["done"] | (e["id"] == F.col("p.id"))).alias("done"))).alias("beam"),
            F.concat("log", F.array(F.struct(F.col("p.dist").alias("dist"), F.col("p.id").alias("id")))).alias("log"), "comps", "live", F.col("p.id").alias("at"),
        )
        met = moved.select("qid", "qvec", "at", F.col("beam.id").alias("in_beam"), F.col("log.id").alias("in_log")).join(lists, F.col("at") == F.col("src"))
        fresh = met.select("qid", "qvec", F.explode(F.array_except(F.array_except("nbrs", "in_beam"), "in_log")).alias("dst"))
        near = fresh.join(vecs, "dst").select("qid", expression(metric, "x", "qvec").alias("dist"), F.col("dst").alias("id"))
        came = near.groupBy("qid").agg(F.collect_list(F.struct("dist", "id", F.lit(False).alias("done"))).cast(BEAM).alias("new"))
        merged = moved.join(came, "qid", "left").select(
            "qid", "qvec", F.slice(F.array_sort(F.concat("beam", F.coalesce("new", F.array().cast(BEAM)))), 1, width).alias("beam"), "log",
            (F.col("comps") + F.coalesce(F.size("new"), F.lit(0))).alias("comps"), "live",
        )
        state = settle(merged.unionByName(state.filter("not live")), "beam")
    return state


def search_rounds(edges: DataFrame, points: PointSet, queries: PointSet, k: int, width: int, start: int, eps: float | None = None) -> SearchResult:
    state = beam_rounds(edges, points, queries, width, start, k, eps)
    found = state.select("qid", F.explode("log").alias("e")).select("qid", F.col("e.id").alias("id"), F.col("e.dist").alias("dist"))
    stats = state.select("qid", F.size("log").cast("long").alias("hops"), F.col("comps").alias("dist_comps"), F.size("log").cast("long").alias("visited"))
    return SearchResult(top_k(found, k), stats)


def insert_rounds(edges: DataFrame, points: PointSet, batch: PointSet, degree: int, width: int, alpha: float, start: int) -> DataFrame:
    """One batch insertion over the snapshot `edges`: search, prune, and merge the reversed edges."""
    state = beam_rounds(edges, points, batch, width, start)
    cand = state.select(F.col("qid").alias("src"), F.explode("log").alias("e")).select("src", F.col("e.id").alias("dst"), F.col("e.dist").alias("dist")).filter("src <> dst")
    new = settle(alpha_prune(cand, points, degree, alpha), "forward")
    grown = merge_reverse(edges, new, points, degree, alpha)
    return settle(grown.unionByName(new).dropDuplicates(["src", "dst"]), "edges")


def build_rounds(points: PointSet, degree: int, width: int, alpha: float, theta: float = 0.02, rule: str = "inclusive", seed: int = 42) -> tuple[DataFrame, int]:
    """The whole incremental build by join rounds: (edges, start)."""
    from proxigraph.operators.exact import medoid

    spark = points.df.sparkSession
    start = medoid(points).first()["id"]
    rest = PointSet(points.plain().filter(F.col("id") != start), metric=points.metric)
    order = settle(rest.ordered(seed), "order")
    n = order.count()
    edges = spark.createDataFrame([], "src long, dst long, dist double")
    for lo, hi in schedule(n, max(1, -(-(n + 1) * int(theta * 1e6) // 1_000_000)), rule):
        batch = PointSet(order.filter(F.col("pos").between(lo, hi)), metric=points.metric)
        edges = insert_rounds(edges, points, batch, degree, width, alpha, start)
    return edges, start
