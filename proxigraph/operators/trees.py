"""Random cluster trees level by level, as DataFrame plans over (tree, id, path)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.functions.distance import expression
from proxigraph.functions.prng import draw
from proxigraph.operators.model import PointSet
from proxigraph.runtime import broadcast_if_small, settle

#: Points of a node below which its leaves are grown in one task.
NODE_ROWS = 8192


def plant(points: PointSet, trees: int = 1) -> DataFrame:
    """tree, id, path: all points in the root of each tree."""
    every = F.explode(F.sequence(F.lit(0), F.lit(trees - 1))).alias("tree")
    return points.plain().select(every, "id", F.lit("").alias("path"))


def _drawn(members: DataFrame, seed: int) -> DataFrame:
    """tree, path, a, b: the member with the least draw, and the one with the least draw among those
    with another vector; two aggregations to one small row per node."""
    m = members.withColumn("h", draw(seed, F.col("tree"), F.col("path"), F.col("id")))
    first = m.groupBy("tree", "path").agg(F.min(F.struct("h", "id", "vec")).alias("x")).select("tree", "path", F.col("x.vec").alias("a"))
    first = broadcast_if_small(settle(first, "first-pivots"))
    other = m.join(first, ["tree", "path"]).filter("vec <> a").groupBy("tree", "path").agg(F.min(F.struct("h", "id", "vec")).alias("x"))
    return first.join(other.select("tree", "path", F.col("x.vec").alias("b")), ["tree", "path"], "left")


def split_level(assigned: DataFrame, points: PointSet, leaf: int = 0, kind: str = "pivots", seed: int = 42) -> DataFrame:
    """One more level: members of every node with more than `leaf` points get "0" or "1" appended.

    "pivots": the nearer of two drawn members, the first among equals. "hyperplane": the side of the
    plane with a drawn +-1 normal through the middle of the two members' projections. Nodes whose
    points are all equal stay as they are.
    """
    vecs = points.plain()
    # a row a node, which is few next to the points: a node that holds most points is no join key
    counts = broadcast_if_small(settle(assigned.groupBy("tree", "path").count(), "node-sizes"))
    sized = assigned.join(counts, ["tree", "path"])
    open_ = settle(sized.filter(F.col("count") > leaf).join(vecs, "id").select("tree", "id", "path", "vec"), "open-nodes")
    nodes = broadcast_if_small(settle(_drawn(open_, seed), "node-pivots"))
    met = open_.join(nodes, ["tree", "path"])
    if kind == "pivots":
        one = expression(points.metric, "vec", "a") > expression(points.metric, "vec", "b")
    else:
        met = met.withColumn("w", F.transform(F.sequence(F.lit(0), F.size("vec") - 1), lambda j: F.when(
            draw(seed, F.col("tree"), F.col("path"), F.lit("dim"), j).bitwiseAND(1) == 1, 1.0).otherwise(-1.0)))

        def side(v):
            return F.aggregate(F.zip_with("w", v, lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)

        one = side("vec") > (side("a") + side("b")) / 2.0
    bit = F.when(F.col("b").isNull(), "").when(one, "1").otherwise("0")
    done = sized.filter(F.col("count") <= leaf).select("tree", "id", "path")
    return met.select("tree", "id", F.concat("path", bit).alias("path")).unionByName(done)


def grow(points: PointSet, levels: int, trees: int = 1, leaf: int = 0, kind: str = "pivots", seed: int = 42) -> DataFrame:
    out = plant(points, trees)
    for _ in range(levels):
        out = settle(split_level(out, points, leaf, kind, seed), "tree")
    return out


def grow_leaves(points: PointSet, trees: int, leaf: int, kind: str = "pivots", seed: int = 42) -> DataFrame:
    """tree, id, path: nodes are split until none has more than `leaf` points; copies of one vector, which
    no split separates, are halved by draw. A level is a few settled tables while a node has more than
    NODE_ROWS points; what is below smaller nodes is grown in a task each."""
    leaf, last = max(leaf, NODE_ROWS), leaf
    assigned = settle(plant(points, trees), "tree")
    level = -1
    while True:  # a node that one draw does not split is split by a later one
        level += 1
        sizes = assigned.groupBy("tree", "path").count().filter(F.col("count") > leaf)
        if sizes.isEmpty():
            break
        split = settle(split_level(assigned, points, leaf, kind, seed), "tree")
        stuck = split.join(assigned.withColumnRenamed("path", "was"), ["tree", "id"]).filter("path = was")
        big = settle(stuck.join(sizes.withColumnRenamed("count", "n"), ["tree", "path"]).select("tree", "id"), "stuck")
        if not big.isEmpty():
            half = (draw(seed, F.col("tree"), F.lit("half"), F.lit(level), F.col("id")) % 2).cast("string")
            hit = split.join(big.withColumn("h", F.lit(1)), ["tree", "id"], "left")
            split = settle(hit.select("tree", "id", F.when(F.col("h") == 1, F.concat("path", half)).otherwise(F.col("path")).alias("path")), "tree")
        assigned = split
    return settle(_below(assigned, points, last, kind, seed), "tree") if last < leaf else assigned


def _below(assigned: DataFrame, points: PointSet, leaf: int, kind: str, seed: int) -> DataFrame:
    """tree, id, path of the leaves below every node, each node in one task."""
    import numpy as np
    import pyarrow as pa

    from proxigraph.operators.kernels import tree_leaves
    from proxigraph.operators.model import to_matrix
    from proxigraph.runtime import ship

    metric = points.metric
    ship(points.df.sparkSession)

    def one(table: pa.Table) -> pa.Table:
        table = table.sort_by("id").combine_chunks()
        tree, root = (table.column(c)[0].as_py() for c in ("tree", "path"))
        ids = table.column("id").to_numpy()
        paths = np.empty(len(ids), dtype=object)
        for path, own in tree_leaves(to_matrix(table.column("vec")).T, ids, leaf, tree, kind, seed, metric, root):
            paths[own] = path
        return pa.table({"tree": pa.array(np.full(len(ids), tree), pa.int32()), "id": pa.array(ids, pa.int64()), "path": pa.array(paths, pa.string())})

    return assigned.join(points.plain(), "id").select("tree", "id", "path", "vec").groupBy("tree", "path").applyInArrow(one, "tree int, id long, path string")


#: Points of a leaf that one task holds on either side.
LEAF_BLOCK = 8192


def leaf_neighbours(assigned: DataFrame, points: PointSet, k: int) -> DataFrame:
    """src, dst, dist: each point's k nearest within its leaf. A leaf is cut into blocks by hashed id, a group is a
    pair of its blocks, and only k answers a point leave it."""
    import numpy as np
    import pyarrow as pa

    from proxigraph.operators.edges import nearest
    from proxigraph.operators.exact import nearest_of
    from proxigraph.operators.model import to_matrix
    from proxigraph.runtime import ship

    metric = points.metric
    ship(points.df.sparkSession)
    sizes = assigned.groupBy("tree", "path").agg(F.ceil(F.count("*") / LEAF_BLOCK).alias("many"))
    sizes = broadcast_if_small(settle(sizes, "leaf-sizes"))
    a = assigned.join(points.plain(), "id").join(sizes, ["tree", "path"]).withColumn("own", F.pmod(F.xxhash64("id"), "many"))
    others = F.explode(F.sequence(F.lit(0).cast("long"), F.col("many") - 1))
    # side 0: sources, 1: targets, 2: both, of a block with itself
    left = a.select("tree", "path", F.col("own").alias("i"), others.alias("j"), "id", "vec").withColumn("side", F.when(F.col("i") == F.col("j"), 2).otherwise(0))
    right = a.select("tree", "path", others.alias("i"), F.col("own").alias("j"), "id", "vec").filter("i <> j").withColumn("side", F.lit(1))

    def one(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        side, ids, x = table.column("side").to_numpy(), table.column("id").to_numpy(), to_matrix(table.column("vec"))
        src, dst = side != 1, side != 0
        r, i, d = nearest_of(ids[src], x[src], ids[dst], x[dst], metric, k, None, True)
        return pa.table({"src": pa.array(ids[src][r], pa.int64()), "dst": pa.array(i, pa.int64()), "dist": pa.array(d, pa.float64())})

    met = left.unionByName(right).groupBy("tree", "path", "i", "j").applyInArrow(one, "src long, dst long, dist double")
    return nearest(met.dropDuplicates(["src", "dst"]), k)


def leaf_trees(assigned: DataFrame, points: PointSet, near: int | None = 10, max_degree: int = 3, key: tuple[str, ...] = ("tree", "path")) -> DataFrame:
    """src, dst, dist: the spanning-tree edges of all leaves, grouped by `key` into tasks."""
    import numpy as np
    import pyarrow as pa

    from proxigraph.operators.kernels import leaf_mst
    from proxigraph.operators.model import to_matrix
    from proxigraph.runtime import ship

    metric = points.metric
    ship(points.df.sparkSession)

    def one(table: pa.Table) -> pa.Table:
        ids = table.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        table = table.take(pa.array(order)).combine_chunks()
        ids, paths = ids[order], np.array(table.column("path").to_pylist())
        vecs = to_matrix(table.column("vec")).T
        edges = [e for p in np.unique(paths) for e in leaf_mst(vecs, np.flatnonzero(paths == p), near, max_degree, metric)]
        a, b = (ids[np.array([e[k] for e in edges], dtype=np.int64)] for k in (0, 1))
        return pa.table({"src": pa.array(a, pa.int64()), "dst": pa.array(b, pa.int64()), "dist": pa.array([e[2] for e in edges], pa.float64())})

    members = assigned.join(points.plain(), "id").select("tree", "path", "id", "vec")
    return members.groupBy(*key).applyInArrow(one, "src long, dst long, dist double")


def tree_mst_edges(
    points: PointSet, trees: int = 30, leaf: int = 1000, near: int | None = 10, max_degree: int = 3, degree: int = 64, alpha: float = 1.0,
    seed: int = 42, parallel: str = "leaves",
) -> DataFrame:
    """src, dst, dist of a tree-MST graph over all points at once, without shards.

    All nodes of a level are split together, one settled table a level; a leaf, at most `leaf` points
    (copies of one vector apart, which no pivot separates and which are halved by draw), is one task's
    work. parallel "trees": one task per tree instead, as a baseline; the edges are the same.
    """
    from proxigraph.operators.edges import alpha_prune, union_local

    assigned = grow_leaves(points, trees, leaf, "pivots", seed)
    made = settle(leaf_trees(assigned, points, near, max_degree, ("tree", "path") if parallel == "leaves" else ("tree",)), "leaf-edges")
    both = union_local(made, made.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist"))
    return alpha_prune(both, points, degree, alpha)


def descent_edges(
    points: PointSet, trees: int = 10, leaf: int = 100, k: int = 40, degree: int = 64, alpha: float = 1.2, cap: int | None = 2000, delta: float = 0.001,
    max_rounds: int = 20, blocks: int = 1, seed: int = 42,
) -> tuple[DataFrame, int]:
    """(src, dst, dist) of a descent graph over all points at once, by rounds of joins, and the number
    of rounds: it stops when at most delta * n * k edges are new."""
    from proxigraph.operators.edges import alpha_prune, changed, descent_round, nearest, undirect

    n = points.df.count()
    assigned = grow_leaves(points, trees, leaf, "hyperplane", seed)
    edges = settle(nearest(leaf_neighbours(assigned, points, k).dropDuplicates(["src", "dst"]), k), "descent")
    rounds, before, whole = 0, None, False
    while rounds < max_rounds:
        was = whole
        whole = cap is None or (undirect(edges).groupBy("src").count().agg(F.max("count")).first()[0] or 0) <= cap
        after = settle(descent_round(edges, points, k, cap, seed, rounds, blocks, before if was and whole else None), "descent")
        rounds += 1
        new = changed(edges, after).count()
        before, edges = edges, after
        if new <= delta * n * k:
            break
    return alpha_prune(undirect(edges), points, degree, alpha), rounds
