"""Measures of accuracy and cost, and the sweeps that produce them."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxigraph.operators.model import PointSet

RUNS = "run_id string, method string, params map<string,string>, metric string, value double"


def recall(truth: DataFrame, found: DataFrame, queries: DataFrame, k: int = 10, kp: int | None = None) -> DataFrame:
    """qid, recall: the share of each query's k true neighbours among its first kp answers; a query
    without answers counts 0. queries has qid."""
    t = truth.filter(F.col("rank") <= k).select("qid", "id")
    hit = t.join(found.filter(F.col("rank") <= (kp or k)).select("qid", "id"), ["qid", "id"], "left_semi").groupBy("qid").agg(F.count("*").alias("hits"))
    return queries.select("qid").join(hit, "qid", "left").select("qid", (F.coalesce("hits", F.lit(0)) / F.lit(float(k))).alias("recall"))


def mean_recall(truth: DataFrame, found: DataFrame, queries: DataFrame, k: int = 10, kp: int | None = None) -> DataFrame:
    """One row: recall over all queries. Hits are summed as integers, so the order of rows is nothing."""
    r = recall(truth, found, queries, k, kp)
    return r.agg((F.sum(F.round(F.col("recall") * k).cast("long")) / (F.count("*") * F.lit(float(k)))).alias("recall"))


def range_recall(truth: DataFrame, found: DataFrame, queries: DataFrame, empty: str = "zero") -> DataFrame:
    """One row: mean share of the true answers that were reported. empty: queries without true answers
    count 0 ("zero"), are left out ("skip") or count 1 ("one")."""
    n = truth.groupBy("qid").agg(F.count("*").alias("n"))
    hit = truth.select("qid", "id").join(found.select("qid", "id").distinct(), ["qid", "id"], "left_semi").groupBy("qid").agg(F.count("*").alias("hits"))
    all_ = queries.select("qid").join(n, "qid", "left").join(hit, "qid", "left")
    share = F.when(F.col("n") > 0, F.coalesce("hits", F.lit(0)) / F.col("n"))
    share = F.coalesce(share, F.lit(1.0)) if empty == "one" else F.coalesce(share, F.lit(0.0)) if empty == "zero" else share
    return all_.agg(F.round(F.avg(share), 6).alias("range_recall"))


def timed(action: Callable[[], object]) -> tuple[float, object]:
    began = time.perf_counter()
    out = action()
    return time.perf_counter() - began, out


def drain(df: DataFrame) -> None:
    """Compute every row of df and keep none."""
    df.write.format("noop").mode("overwrite").save()


def sweep(spark: SparkSession, method: str, search: Callable[..., object], queries: PointSet, truth: DataFrame, grid: list[dict], k: int = 10) -> DataFrame:
    """Long table of runs: recall, comparisons per query and queries per second of each setting."""
    rows = []
    ids = queries.plain().select(F.col("id").alias("qid"))
    n = max(1, ids.count())
    for i, params in enumerate(grid):
        seconds, out = timed(lambda params=params: search(queries, k, **params))
        both = recall(truth, out.results, ids, k).join(out.stats.select("qid", "dist_comps"), "qid", "left")
        spent, r = timed(lambda both=both: both.agg(F.sum(F.round(F.col("recall") * k).cast("long")).alias("hits"), F.avg("dist_comps").alias("comps")).first())
        value, comps = r["hits"] / (n * float(k)), r["comps"]
        named = {a: str(b) for a, b in params.items()}
        for metric, x in (("recall", value), ("dist_comps", comps), ("qps", n / (seconds + spent))):
            rows.append((f"{method}-{i}", method, named, metric, float(x if x is not None else 0.0)))
    return spark.createDataFrame(rows, RUNS)


def wide(runs: DataFrame) -> DataFrame:
    """One row per run, a column per metric."""
    return runs.groupBy("run_id", "method", "params").pivot("metric", ["recall", "dist_comps", "qps", "build_s"]).agg(F.first("value"))


def pareto(points: DataFrame, recall_col: str = "recall", gain: str = "qps") -> DataFrame:
    """Rows of (method, recall, gain) that no other row of the method beats in both."""
    above = Window.partitionBy("method").orderBy(F.desc(recall_col), F.desc(gain)).rowsBetween(Window.unboundedPreceding, -1)
    best = F.max(gain).over(above)
    return points.withColumn("_b", best).filter(F.col("_b").isNull() | (F.col(gain) > F.col("_b"))).drop("_b")


def growth(sizes: DataFrame) -> DataFrame:
    """method, n, value -> factor to the next smaller size."""
    return sizes.withColumn("factor", F.col("value") / F.lag("value").over(Window.partitionBy("method").orderBy("n")))


def slowdown(runs: DataFrame) -> DataFrame:
    """method, queries ("same" or "other"), qps, dist_comps at one recall -> what the other distribution
    costs: queries per second of the same over the other's, and comparisons of the other's over the same."""
    same = runs.filter("queries = 'same'").select("method", F.col("qps").alias("_q"), F.col("dist_comps").alias("_c"))
    other = runs.filter("queries = 'other'").select("method", "qps", "dist_comps")
    return other.join(same, "method").select("method", (F.col("_q") / F.col("qps")).alias("qps_slowdown"), (F.col("dist_comps") / F.col("_c")).alias("comps_slowdown"))


def speedup(runs: DataFrame, base: str = "original") -> DataFrame:
    """method, variant, threads, seconds -> over the original at one thread, and over itself at one."""
    one = runs.filter((F.col("variant") == base) & (F.col("threads") == 1)).select("method", F.col("seconds").alias("_o"))
    own = runs.filter("threads = 1").select("method", "variant", F.col("seconds").alias("_s"))
    return runs.join(one, "method").join(own, ["method", "variant"]).select("method", "variant", "threads", (F.col("_o") / F.col("seconds")).alias("over_original"), (F.col("_s") / F.col("seconds")).alias("over_self"))


def tune_to_recall(search: Callable[..., object], queries: PointSet, truth: DataFrame, target: float = 0.8, k: int = 10, low: int | None = None, most: int = 4096, knob: str = "width") -> dict:
    """The least value of the knob that reaches the recall, by doubling and bisection, with its recall,
    comparisons per query and queries per second. reached is False if `most` does not reach it."""
    ids = queries.plain().select(F.col("id").alias("qid"))

    n = max(1, ids.count())

    def at(x: int) -> tuple[float, float, float]:
        seconds, out = timed(lambda: search(queries, k, **{knob: x}))
        return mean_recall(truth, out.results, ids, k).first()["recall"], out.stats.agg(F.avg("dist_comps")).first()[0], n / seconds

    lo, hi = 0, low or k
    got = at(hi)
    while got[0] < target and hi < most:
        lo, hi = hi, min(hi * 2, most)
        got = at(hi)
    while got[0] >= target and hi - lo > max(1, hi // 16):
        mid = (lo + hi) // 2
        if mid < (low or k):
            break
        mine = at(mid)
        lo, hi, got = (lo, mid, mine) if mine[0] >= target else (mid, hi, got)
    return {knob: hi, "recall": got[0], "dist_comps": got[1], "qps": got[2], "reached": got[0] >= target}


def bytes_per_vector(rows: DataFrame) -> DataFrame:
    """One row: mean bytes of a point's vector and of its neighbour list, as stored plainly."""
    return rows.agg(F.avg(F.size("vec") * 8).alias("vector_bytes"), F.avg(F.size("nbrs") * 8).alias("list_bytes"))
