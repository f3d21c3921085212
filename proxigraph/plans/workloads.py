"""The experiment workloads on the given tables: long tables of measured runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxigraph.operators import carriers, exact, hashing, index, inverted, measures, quantise
from proxigraph.operators.model import PointSet
from proxigraph.runtime import settle

QUERIES: dict = {}

#: Build parameters scaled to tables of thousands of points.
BUILDS = {
    "alpha": {"degree": 32, "width": 64}, "layered": {"m": 16, "width": 64}, "tree_mst": {"trees": 10, "leaf": 200}, "descent": {"trees": 5, "leaf": 100, "k": 20, "degree": 32},
}
WIDTHS = (10, 20, 40, 80, 160)
#: Early stops swept together with the widths; None: no early stop.
EPS = (0.1, None)
LIST_ITERATIONS = 5
#: Points that one shard holds where tables grow.
SHARD = 10_000


def workload(f):
    QUERIES[f.__name__] = f
    return f


def _carrier(spark, sf_dir, name: str) -> tuple[PointSet, PointSet]:
    p = {"emb": carriers.emb, "emb8": carriers.emb8, "doc": carriers.doc, "web": carriers.web}[name](spark, sf_dir)
    return PointSet(settle(p.plain(), f"carrier-{name}")).split_queries(10 if name != "doc" else 20)


def _probes(cells: int) -> list[int]:
    return sorted({min(p, cells) for p in (1, 2, max(3, cells // 8), max(4, cells // 2), cells)})


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, measures.RUNS)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _curves(spark, sf_dir, names, methods=tuple(BUILDS), widths=WIDTHS, eps=EPS) -> DataFrame:
    """Recall, comparisons and queries per second of all methods along their knobs: beam width and early
    stop together, or the number of lists."""
    parts = []
    for name in names:
        base, q = _carrier(spark, sf_dir, name)
        truth = settle(exact.exact_knn(base, q, 10), "truth")
        n = base.df.count()
        for m in methods:
            seconds, g = measures.timed(lambda m=m, base=base: index.BUILDERS[m](base, **BUILDS[m]))
            parts.append(measures.sweep(spark, f"{m}/{name}", g.search, q, truth, [{"width": w} | ({} if e is None else {"eps": e}) for w in widths for e in eps]))
            parts.append(_rows(spark, [(f"{m}/{name}", f"{m}/{name}", {}, "build_s", seconds)]))
        cells = max(2, int(n ** 0.5))
        seconds, i = measures.timed(lambda base=base, cells=cells: inverted.InvertedIndex.build(base, cells, LIST_ITERATIONS))
        parts.append(measures.sweep(spark, f"inverted/{name}", i.search, q, truth, [{"probe": p} for p in _probes(cells)]))
        parts.append(_rows(spark, [(f"inverted/{name}", f"inverted/{name}", {}, "build_s", seconds)]))
    return _union(parts)


@workload
def w01_curves_qps(spark, sf_dir):
    """Recall and queries per second of every setting, and whether no other setting of the method beats it
    in both."""
    wide = settle(measures.wide(_curves(spark, sf_dir, ["emb", "doc", "web"])).filter("recall IS NOT NULL"), "curves")
    best = measures.pareto(wide).select("run_id", F.lit(True).alias("front"))
    return wide.join(best, "run_id", "left").select("run_id", "method", "params", "recall", "qps", "dist_comps", F.coalesce("front", F.lit(False)).alias("front"))


@workload
def w02_curves_comps(spark, sf_dir):
    return _curves(spark, sf_dir, ["emb", "doc", "web"]).filter("metric IN ('recall', 'dist_comps')")


@workload
def w03_high_recall(spark, sf_dir):
    wide = measures.wide(_curves(spark, sf_dir, ["emb", "doc", "web"], widths=(50, 100, 200), eps=(None,)))
    return wide.filter("recall >= 0.9").select("run_id", "method", "recall", "dist_comps")


@workload
def w04_build_table(spark, sf_dir):
    """Build seconds of five methods on three carriers, one row per method."""
    rows = []
    for name in ("emb", "doc", "web"):
        base, _ = _carrier(spark, sf_dir, name)
        for m in BUILDS:
            rows.append((m, name, measures.timed(lambda m=m, base=base: index.BUILDERS[m](base, **BUILDS[m]))[0]))
        rows.append(("inverted", name, measures.timed(lambda base=base: inverted.InvertedIndex.build(base, max(2, int(base.df.count() ** 0.5)), 5))[0]))
    return spark.createDataFrame(rows, "method string, carrier string, seconds double").groupBy("method").pivot("carrier", ["emb", "doc", "web"]).agg(F.first("seconds"))


@workload
def w05_one_thread_qps(spark, sf_dir):
    """Queries per second of the kernel in one task."""
    base, q = _carrier(spark, sf_dir, "doc")
    g = index.alpha_graph(base, **BUILDS["alpha"])
    one = PointSet(q.df.coalesce(1))
    n = q.df.count()
    return _rows(spark, [(f"alpha-{w}", "alpha", {"width": str(w)}, "qps", n / measures.timed(lambda w=w: measures.drain(g.search(one, 10, w).results))[0]) for w in WIDTHS])


@workload
def w06_old_and_new(spark, sf_dir):
    """Build seconds of the original schedules and layouts against ours, same parameters, by threads, with
    the speedups over the original at one thread and over itself at one.

    The originals insert one point at a time (alpha, layered), use all pairs of a leaf and a task per tree
    (tree-MST) or an uncapped degree and one block (descent). The batch engine and the join rounds of the
    trees share their work among a given number of tasks, so one session measures the curve."""
    base, _ = _carrier(spark, sf_dir, "doc")
    cores = spark.sparkContext.defaultParallelism
    threads = [t for t in (1, 2, 4, 8, 16, 32) if t <= cores]

    def sharded(build, t, **kw):
        return lambda: build(base, shard_rows=max(1, -(-base.df.count() // t)), shard_kind="hash", **kw)

    kinds = [("alpha", "original", 1, lambda: index.alpha_graph(base, 32, 64, rule="sequential"))]
    kinds += [("alpha", "ours", t, lambda t=t: index.alpha_graph(base, 32, 64, engine="batches", tasks=t)) for t in threads]
    kinds.append(("layered", "original", 1, lambda: index.layered_graph(base, 16, 64, rule="sequential")))
    kinds += [("layered", "ours", t, sharded(index.layered_graph, t, m=16, width=64)) for t in threads]
    kinds.append(("tree_mst", "original", 1, lambda: index.tree_mst_graph(base, 10, 200, None)))
    kinds += [("tree_mst", "ours", t, sharded(index.tree_mst_graph, t, trees=10, leaf=200)) for t in threads]
    kinds.append(("descent", "original", 1, lambda: index.descent_graph(base, 5, 100, 20, 32, cap=None, block=1 << 30)))
    kinds += [("descent", "ours", t, sharded(index.descent_graph, t, trees=5, leaf=100, k=20, degree=32)) for t in threads]
    rows = [(m, variant, t, measures.timed(f)[0]) for m, variant, t, f in kinds]
    runs = settle(spark.createDataFrame(rows, "method string, variant string, threads int, seconds double"), "runs")
    return runs.join(measures.speedup(runs), ["method", "variant", "threads"])


def _sizes(spark, sf_dir) -> list[tuple[str, int, PointSet, PointSet]]:
    """(carrier, points, base, queries): shares of the line items and of the documents, each table whole at
    last."""
    out = []
    for name, p, shares, mod in (("num", carriers.num(spark, sf_dir), (0.01, 0.1, 1.0), 50), ("doc", carriers.doc(spark, sf_dir), (0.2, 1.0), 20)):
        p = PointSet(settle(p.plain(), f"carrier-{name}"))
        for share in shares:
            part = p.sample(share) if share < 1 else p
            out.append((name, part.df.count(), *part.split_queries(mod)))
    return out


@workload
def w07_size_scaling(spark, sf_dir):
    """Build seconds, and width, comparisons and queries per second at recall 0.8, as the table grows, with
    the growth of the build; shards of SHARD points, as a cluster would have them."""
    rows = []
    for name, n, base, q in _sizes(spark, sf_dir):
        truth = settle(exact.exact_knn(base, q, 10), "truth")
        for m in BUILDS:
            seconds, g = measures.timed(lambda m=m, base=base: index.BUILDERS[m](base, shard_rows=SHARD, **BUILDS[m]))
            tuned = measures.tune_to_recall(g.search, q, truth, 0.8)
            rows.append((f"{m}/{name}", n, seconds, tuned["width"], tuned["recall"], tuned["dist_comps"], tuned["qps"], tuned["reached"]))
        cells = max(2, int(n ** 0.5))
        seconds, i = measures.timed(lambda base=base, cells=cells: inverted.InvertedIndex.build(base, cells, LIST_ITERATIONS))
        tuned = measures.tune_to_recall(i.search, q, truth, 0.8, low=1, most=cells, knob="probe")
        rows.append((f"inverted/{name}", n, seconds, tuned["probe"], tuned["recall"], tuned["dist_comps"], tuned["qps"], tuned["reached"]))
    runs = spark.createDataFrame(rows, "method string, n long, value double, knob long, recall double, dist_comps double, qps double, reached boolean")
    return measures.growth(runs).withColumnRenamed("value", "build_s").withColumnRenamed("factor", "build_growth")


@workload
def w08_out_of_distribution(spark, sf_dir):
    """Comparisons and queries per second at recall 0.8 for queries of the points' own and of another
    distribution, and the slowdown: passages as unit vectors against embeddings, and what users say in
    chats against documents."""
    rows = []
    for carrier, other in (("emb", carriers.ood(spark, sf_dir)), ("doc", carriers.conv(spark, sf_dir))):
        base, q = _carrier(spark, sf_dir, carrier)
        other = PointSet(settle(other.plain(), "other-queries"))
        graphs = {m: index.BUILDERS[m](base, **BUILDS[m]) for m in BUILDS}
        lists = inverted.InvertedIndex.build(base, max(2, int(base.df.count() ** 0.5)), LIST_ITERATIONS)
        for name, qs in (("same", q), ("other", other)):
            truth = settle(exact.exact_knn(base, qs, 10), "truth")
            for m, g in graphs.items():
                t = measures.tune_to_recall(g.search, qs, truth, 0.8)
                rows.append((f"{m}/{carrier}", name, t["width"], t["recall"], t["dist_comps"], t["qps"], t["reached"]))
            t = measures.tune_to_recall(lists.search, qs, truth, 0.8, low=1, most=lists.lists, knob="probe")
            rows.append((f"inverted/{carrier}", name, t["probe"], t["recall"], t["dist_comps"], t["qps"], t["reached"]))
    runs = settle(spark.createDataFrame(rows, "method string, queries string, knob long, recall double, dist_comps double, qps double, reached boolean"), "runs")
    return runs.join(measures.slowdown(runs), "method")


@workload
def w09_range_queries(spark, sf_dir):
    """Range recall and comparisons: graph variants against lists, for near copies of documents and for
    documents near benchmark passages."""
    base, q = _carrier(spark, sf_dir, "doc")
    i = inverted.InvertedIndex.build(base, max(2, int(base.df.count() ** 0.5)), LIST_ITERATIONS)
    g = index.alpha_graph(base, **BUILDS["alpha"])
    passages = PointSet(settle(carriers.bench_text(spark, sf_dir).plain(), "passages"))
    rows = []
    for kind, qs, radius in (("near copies", q, 6.0), ("passages", passages, 12.0)):
        ids = qs.plain().select(F.col("id").alias("qid"))
        truth = settle(exact.exact_range(base, qs, radius), "truth")
        for name, kw in (("beam", {}), ("flood", {"flood": True}), ("grow", {"grow": True})):
            out = g.range_search(qs, radius, 32, **kw)
            rows.append((kind, name, measures.range_recall(truth, out.results, ids, "skip").first()[0], out.stats.agg(F.avg("dist_comps")).first()[0], truth.count()))
        for p in (1, 4, 16):
            rows.append((kind, f"lists-{p}", measures.range_recall(truth, i.range_search(qs, radius, p), ids, "skip").first()[0], i.search(qs, 10, p).stats.agg(F.avg("dist_comps")).first()[0], truth.count()))
    return spark.createDataFrame([(k, a, float(b or 0), float(c), n) for k, a, b, c, n in rows], "queries string, variant string, range_recall double, dist_comps double, true_answers long")


@workload
def w10_bytes_and_floats(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "emb")
    base8, q8 = quantise.sq8(base), quantise.sq8(q)
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    parts = [measures.sweep(spark, name, index.alpha_graph(b, **BUILDS["alpha"]).search, qs, truth, [{"width": w} for w in (20, 100)]) for name, b, qs in (("float", base, q), ("byte", base8, q8))]
    return _union(parts).filter("metric <> 'qps'")


@workload
def w11_determinism(spark, sf_dir):
    """Fingerprints of one build under several layouts of the input."""
    base, _ = _carrier(spark, sf_dir, "emb")
    rows = []
    for m in BUILDS:
        for parts in (1, 7, 64):
            print_, n = index.BUILDERS[m](PointSet(base.df.repartition(parts)), **BUILDS[m]).fingerprint()
            rows.append((m, parts, print_, n))
    return spark.createDataFrame(rows, "method string, partitions int, print long, edges long")


@workload
def w12_doubling_and_sequential(spark, sf_dir):
    kinds = {"doubling": {}, "sequential": {"rule": "sequential"}, "one shot": {"rule": "single"}, "uncapped": {"theta": 1.0}}
    parts = []
    for name in ("emb", "doc"):
        base, q = _carrier(spark, sf_dir, name)
        truth = settle(exact.exact_knn(base, q, 10), "truth")
        parts += [measures.sweep(spark, f"{k}/{name}", index.alpha_graph(base, 64, 128, **kw).search, q, truth, [{"width": w} for w in (20, 50, 100)]) for k, kw in kinds.items()]
    return _union(parts).filter("metric <> 'qps'")


@workload
def w13_restricted_mst(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "doc")
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    return _union([measures.sweep(spark, f"near {near}", index.tree_mst_graph(base, 10, 200, near).search, q, truth, [{"width": w} for w in (20, 100)]) for near in (10, None)]).filter("metric <> 'qps'")


@workload
def w14_descent_caps(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "doc")
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    kinds = {"cap 2000": {}, "cap 50": {"cap": 50}, "no cap": {"cap": None}, "small blocks": {"block": 64}}
    return _union([measures.sweep(spark, k, index.descent_graph(base, 5, 100, 20, 32, **kw).search, q, truth, [{"width": 50}]) for k, kw in kinds.items()]).filter("metric <> 'qps'")


@workload
def w15_visited_tables(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "emb")
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    g = index.alpha_graph(base, **BUILDS["alpha"])
    return measures.sweep(spark, "alpha", g.search, q, truth, [{"width": w, "visited": v} for w in (20, 50) for v in ("exact", "lossy", "seen")])


@workload
def w16_width_and_eps(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "emb")
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    g = index.alpha_graph(base, **BUILDS["alpha"])
    return measures.sweep(spark, "alpha", g.search, q, truth, [{"width": w, "eps": e} for w in (10, 50, 200) for e in (0.0, 0.1, 0.25, None)]).filter("metric <> 'qps'")


@workload
def w17_list_plateau(spark, sf_dir):
    parts = []
    for name in ("emb", "doc"):
        base, q = _carrier(spark, sf_dir, name)
        truth = settle(exact.exact_knn(base, q, 10), "truth")
        cells = max(2, int(base.df.count() ** 0.5))
        i = inverted.InvertedIndex.build(base, cells, 5)
        parts.append(measures.sweep(spark, name, i.search, q, truth, [{"probe": p} for p in sorted({1, 2, 4, 8, cells})]))
    return _union(parts).filter("metric <> 'qps'")


@workload
def w18_hash_baseline(spark, sf_dir):
    base, q = _carrier(spark, sf_dir, "emb")
    truth = settle(exact.exact_knn(base, q, 10), "truth")
    return _union([measures.sweep(spark, kind, hashing.HashIndex.build(base, kind, 8, 10).search, q, truth, [{"probes": p} for p in (1, 4)]) for kind in ("sign", "cross")]).filter("metric <> 'qps'")


@workload
def w19_descent_rounds(spark, sf_dir):
    """Rounds until the descent converges, as the table grows; the most of any shard."""
    rows = []
    for name, n, base, _ in _sizes(spark, sf_dir):
        g = index.descent_graph(base, 5, 100, 15, 24, shard_rows=SHARD)
        rows.append((name, n, g.shards.count, g.rows.agg(F.max("rounds")).first()[0]))
    return spark.createDataFrame(rows, "carrier string, n long, shards int, rounds long")


@workload
def w20_prompt_retrieval(spark, sf_dir):
    """Recall of graph search for the documents to put before each user turn."""
    base = PointSet(settle(carriers.doc(spark, sf_dir).plain(), "carrier-doc"))
    q = carriers.conv(spark, sf_dir)
    truth = settle(exact.exact_knn(base, q, 3), "truth")
    g = index.alpha_graph(base, **BUILDS["alpha"])
    return measures.sweep(spark, "alpha", g.search, q, truth, [{"width": w} for w in (10, 50)], 3).filter("metric <> 'qps'")
