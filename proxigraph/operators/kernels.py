"""Graph kernels on one shard: pure functions of arrays, run inside tasks.

Vectors are given by dimension (d x n, best as the transpose of contiguous rows), neighbour lists as
an n x R table padded with -1.
Searches and prunes advance many queries in step, so that a step costs a few array operations
whatever the number of queries; every choice is ordered by (distance, id), so results depend on
nothing else.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import dataclass, field

import numpy as np

from proxigraph.functions.distance import close_pairs, gathered
from proxigraph.functions.prng import RANGE, draw_value

QUERY_BLOCK = 256


@dataclass
class Graph:
    """Vectors by dimension, neighbour positions (n x R, -1 pads) and their distances. Positions are
    in ascending order of the ids, so ties by position are ties by id."""

    vecs: np.ndarray
    nbrs: np.ndarray
    dists: np.ndarray
    start: int = 0
    metric: str = "l2"
    upper: list[dict[int, tuple[np.ndarray, np.ndarray]]] = field(default_factory=list)  # layers above the bottom
    entry: int = 0
    comps: int = 0  # distances that trees, leaves and rounds of the build computed

    @property
    def n(self) -> int:
        return self.vecs.shape[1]

    def degree(self) -> np.ndarray:
        return (self.nbrs >= 0).sum(axis=1)


def empty_graph(vecs: np.ndarray, degree: int, start: int = 0, metric: str = "l2") -> Graph:
    n = vecs.shape[1]
    return Graph(np.asfortranarray(vecs), np.full((n, degree), -1, dtype=np.int64), np.full((n, degree), np.inf), start, metric)


@dataclass
class Found:
    """Of each query: processed positions and distances in order (-1 pads), hops, distance
    computations, and the final beam."""

    visited: np.ndarray
    distance: np.ndarray
    hops: np.ndarray
    comps: np.ndarray
    beam: np.ndarray
    beam_distance: np.ndarray
    #: How many vertices were processed, where `visited` holds the nearest of them only.
    processed: np.ndarray | None = None

    def nearest(self, k: int, source: str = "visited") -> tuple[np.ndarray, np.ndarray]:
        """The k closest processed vertices (or beam members) of each query, by (distance, id)."""
        ids, d = (self.visited, self.distance) if source == "visited" else (self.beam, self.beam_distance)
        order = np.lexsort((ids, d), axis=1)[:, : max(k, 1)]
        out, far = np.take_along_axis(ids, order, axis=1), np.take_along_axis(d, order, axis=1)
        again = np.zeros(out.shape, dtype=bool)  # a vertex visited twice counts once
        again[:, 1:] = (out[:, 1:] == out[:, :-1]) & (out[:, 1:] >= 0)
        if again.any():
            full = np.lexsort((ids, d), axis=1)
            ids, d = np.take_along_axis(ids, full, axis=1), np.take_along_axis(d, full, axis=1)
            dup = np.zeros(ids.shape, dtype=bool)
            dup[:, 1:] = (ids[:, 1:] == ids[:, :-1]) & (ids[:, 1:] >= 0)
            d = np.where(dup, np.inf, d)
            ids = np.where(dup, -1, ids)
            keep = np.argsort(d, axis=1, kind="stable")[:, :k]
            return np.take_along_axis(ids, keep, axis=1), np.take_along_axis(d, keep, axis=1)
        return out[:, :k], far[:, :k]


def beam_search(
    graph: Graph, queries: np.ndarray, width: int, k: int = 1, eps: float | None = None, visited: str = "seen",
    starts: np.ndarray | None = None, max_hops: int | None = None,
) -> Found:
    """Beam search of every query (columns of queries) from its start over one snapshot.

    A step processes the closest unprocessed member of the beam; its out-neighbours that are neither
    in the beam nor processed cost one distance each and enter the beam, of which the `width` closest
    stay. With eps, a query ends once that member is beyond (1 + eps) times the k-th distance.
    visited="exact" remembers processed vertices only, so the distance of one that fell out of the beam
    may be computed again; "seen" remembers all that were computed, with the same answers, as the beam
    only gets closer; "lossy" remembers processed vertices in width**2 slots, so some may be forgotten.
    """
    n_q = queries.shape[1]
    parts = []
    step = max(8, min(QUERY_BLOCK, (64 << 20) // max(1, graph.n)))
    for lo in range(0, n_q, step):
        hi = min(lo + step, n_q)
        own = starts[lo:hi] if starts is not None else np.full(hi - lo, graph.start)
        parts.append(_beam_block(graph, np.asfortranarray(queries[:, lo:hi]), width, k, eps, visited, own, max_hops))
    if not parts:
        none = np.empty((0, 0))
        return Found(none.astype(np.int64), none, np.zeros(0, np.int64), np.zeros(0, np.int64), none.astype(np.int64), none)
    most = max(p.visited.shape[1] for p in parts)

    def padded(x: np.ndarray, fill) -> np.ndarray:
        return np.pad(x, ((0, 0), (0, most - x.shape[1])), constant_values=fill)

    return Found(
        np.concatenate([padded(p.visited, -1) for p in parts]), np.concatenate([padded(p.distance, np.inf) for p in parts]),
        np.concatenate([p.hops for p in parts]), np.concatenate([p.comps for p in parts]),
        np.concatenate([p.beam for p in parts]), np.concatenate([p.beam_distance for p in parts]),
    )


def _beam_block(graph: Graph, queries, width, k, eps, visited, starts, max_hops) -> Found:
    b = queries.shape[1]
    who = np.arange(b)
    ids = np.full((b, width), -1, dtype=np.int64)
    dist = np.full((b, width), np.inf)
    done = np.zeros((b, width), dtype=bool)
    ids[:, 0] = starts
    dist[:, 0] = gathered(queries, who, graph.vecs, starts, graph.metric)
    comps, hops = np.ones(b, np.int64), np.zeros(b, np.int64)
    log_ids, log_dist = [], []
    slots = np.full((b, width * width), -1, dtype=np.int64) if visited == "lossy" else None
    # of each query and point: whether it is closed to the beam (processed, or ever computed), or in it
    closed, inside = np.zeros((b, graph.n), dtype=bool), np.zeros((b, graph.n), dtype=bool)
    inside[who, starts] = True
    live = who
    while len(live):
        open_ = (ids[live] >= 0) & ~done[live]
        at = open_.argmax(axis=1)
        go = open_.any(axis=1)
        if eps is not None and k <= width:
            kth = dist[live, k - 1]
            go &= ~(np.isfinite(kth) & (dist[live, at] > (1 + eps) * kth))
        if max_hops is not None:
            go &= hops[live] < max_hops
        live, at = live[go], at[go]
        if not len(live):
            break
        p = ids[live, at]
        done[live, at] = True
        hops[live] += 1
        step_ids, step_dist = np.full(b, -1, dtype=np.int64), np.full(b, np.inf)
        step_ids[live], step_dist[live] = p, dist[live, at]
        log_ids.append(step_ids)
        log_dist.append(step_dist)
        near = graph.nbrs[p]
        fresh = near >= 0
        safe = np.where(fresh, near, 0)
        if slots is None:
            closed[live, p] = True
            fresh &= ~closed[live[:, None], safe]
        else:
            slots[live, _slot(p, width * width)] = p
            fresh &= slots[live[:, None], _slot(safe, width * width)] != near
        fresh &= ~inside[live[:, None], safe]
        comps[live] += fresh.sum(axis=1)
        r, c = np.nonzero(fresh)
        if not len(r):
            continue
        new = np.full(near.shape, np.inf)
        # beyond the last of a full beam no vertex enters it
        new[r, c] = gathered(queries, live[r], graph.vecs, near[r, c], graph.metric, dist[live[r], -1])
        if visited == "seen":
            closed[live[r], near[r, c]] = True
        inside[live[r], near[r, c]] = True
        all_ids = np.concatenate([ids[live], np.where(fresh, near, -1)], axis=1)
        all_dist = np.concatenate([dist[live], new], axis=1)
        all_done = np.concatenate([done[live], np.zeros(near.shape, bool)], axis=1)
        order = np.argsort(all_dist, axis=1, kind="stable")
        ranked = np.take_along_axis(all_dist, order, axis=1)
        tied = np.flatnonzero(((ranked[:, 1:] == ranked[:, :-1]) & np.isfinite(ranked[:, 1:])).any(axis=1))
        if len(tied):  # ties go by id
            order[tied] = np.lexsort((np.where(all_ids[tied] < 0, np.iinfo(np.int64).max, all_ids[tied]), all_dist[tied]), axis=1)
        out = np.take_along_axis(all_ids, order[:, width:], axis=1)
        r, c = np.nonzero(out >= 0)
        inside[live[r], out[r, c]] = False
        order = order[:, :width]
        ids[live] = np.take_along_axis(all_ids, order, axis=1)
        dist[live] = np.take_along_axis(all_dist, order, axis=1)
        done[live] = np.take_along_axis(all_done, order, axis=1)
    log_i = np.stack(log_ids, axis=1) if log_ids else np.empty((b, 0), np.int64)
    log_d = np.stack(log_dist, axis=1) if log_dist else np.empty((b, 0))
    return Found(log_i, log_d, hops, comps, ids, dist)


def _slot(ids: np.ndarray, size: int) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(20)).astype(np.int64) % size


def prune(
    vecs: np.ndarray, own: np.ndarray, cand: np.ndarray, dist: np.ndarray, degree: int, alpha: float = 1.2,
    rule: str = "alpha", metric: str = "l2", keep_pruned: bool = False,
) -> tuple[np.ndarray, np.ndarray]:
    """At most `degree` neighbours of each point own[i] out of cand[i] (-1 pads) at distances dist[i].

    Candidates are taken by (distance, id). rule "alpha": a survivor c drops every later x that it is
    alpha times closer to than the point is, alpha * d(c, x) <= d(own, x). rule "nearest": no drops.
    keep_pruned fills what is left of the degree with the closest dropped candidates.
    """
    if alpha < 1:
        raise ValueError("alpha must be at least 1")
    vecs = np.asfortranarray(vecs)
    b, width = cand.shape
    out, far = np.full((b, degree), -1, dtype=np.int64), np.full((b, degree), np.inf)
    if not width:
        return out, far
    dist = np.where((cand < 0) | (cand == own[:, None]), np.inf, dist)
    order = np.lexsort((cand, dist), axis=1)
    cand, dist = np.take_along_axis(cand, order, axis=1), np.take_along_axis(dist, order, axis=1)
    alive = np.isfinite(dist)
    alive[:, 1:] &= cand[:, 1:] != cand[:, :-1]
    real = alive.copy()
    taken = np.zeros((b, width), dtype=bool)
    count = np.zeros(b, np.int64)
    if rule == "nearest":
        rank = np.cumsum(alive, axis=1)
        taken = alive & (rank <= degree)
        count = taken.sum(axis=1)
    else:
        rows = np.flatnonzero(alive.any(axis=1))
        while len(rows):
            at = alive[rows].argmax(axis=1)
            c = cand[rows, at]
            taken[rows, at] = True
            alive[rows, at] = False
            count[rows] += 1
            r, col = np.nonzero(alive[rows])
            own_dist = dist[rows[r], col]
            drop = alpha * gathered(vecs, c[r], vecs, cand[rows[r], col], metric, own_dist / alpha) <= own_dist
            alive[rows[r[drop]], col[drop]] = False
            rows = rows[(count[rows] < degree) & alive[rows].any(axis=1)]
    if keep_pruned:
        spare = real & ~taken
        rank = np.cumsum(spare, axis=1)
        taken |= spare & (rank <= (degree - count)[:, None])
    r, col = np.nonzero(taken)
    place = (np.cumsum(taken, axis=1) - 1)[r, col]
    out[r, place], far[r, place] = cand[r, col], dist[r, col]
    return out, far


def schedule(n: int, cap: int | None = None, rule: str = "inclusive") -> list[tuple[int, int]]:
    """Batches (first, last) of positions 1..n. "inclusive": the end of a batch is twice its start or
    start + cap, so sizes are 2, 4, 8, ... and at most cap + 1; "doubling": 1, 1, 2, 4, ... of at
    most cap; "single": everything at once; "sequential": one by one."""
    if rule == "single":
        return [(1, n)] if n else []
    if rule == "sequential":
        return [(i, i) for i in range(1, n + 1)]
    cap = max(1, n if cap is None else cap)
    out, at = [], 1
    while at <= n:
        if rule == "inclusive":
            end = min(2 * at, at + cap, n)
        else:
            end = min(at + min(cap, max(1, at - 1)) - 1, n)
        out.append((at, end))
        at = end + 1
    return out


def merged_arrivals(
    graph: Graph, source: np.ndarray, target: np.ndarray, dist: np.ndarray, degree: int, alpha: float, rule: str = "alpha", keep_pruned: bool = False,
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The lists (vertices, neighbours, distances) that edges target -> source change, grouped by target;
    lists beyond the degree are pruned. The graph stays as it is."""
    order = np.lexsort((source, target))
    source, target, dist = source[order], target[order], dist[order]
    used, first, many = np.unique(target, return_index=True, return_counts=True)
    width = graph.nbrs.shape[1]
    nbrs, dists = graph.nbrs[used], graph.dists[used]
    if not len(used):
        return used, nbrs, dists
    cand = np.full((len(used), width + int(many.max())), -1, dtype=np.int64)
    far = np.full(cand.shape, np.inf)
    cand[:, :width], far[:, :width] = nbrs, dists
    row = np.repeat(np.arange(len(used)), many)
    col = width + np.arange(len(source)) - np.repeat(first, many)
    cand[row, col], far[row, col] = source, dist
    fits = (cand >= 0).sum(axis=1) <= degree
    for rows, how in ((np.flatnonzero(fits), "nearest"), (np.flatnonzero(~fits), rule)):
        if len(rows):
            nbrs[rows, :degree], dists[rows, :degree] = prune(graph.vecs, used[rows], cand[rows], far[rows], degree, alpha, how, graph.metric, keep_pruned)
    return used, nbrs, dists


def searched(graph: Graph, batch: np.ndarray, degree: int, width: int, alpha: float, rule: str = "alpha", keep_pruned: bool = False, starts: np.ndarray | None = None, extra: bool = False):
    """Lists (neighbours, distances) of the points at positions `batch`, and the distances computed by
    their searches: each searches the graph as it is and prunes what it visited."""
    found = beam_search(graph, graph.vecs.T[batch].T, width, starts=starts)
    cand, dist = found.visited, found.distance
    if extra:
        cand, dist = np.concatenate([cand, graph.nbrs[batch]], axis=1), np.concatenate([dist, graph.dists[batch]], axis=1)
    return *prune(graph.vecs, batch, cand, dist, degree, alpha, rule, graph.metric, keep_pruned), int(found.comps.sum())


def insert_batch(
    graph: Graph, batch: np.ndarray, degree: int, width: int, alpha: float, rule: str = "alpha", keep_pruned: bool = False,
    starts: np.ndarray | None = None, extra: bool = False,
) -> int:
    """Insert the points at positions `batch`: all search the graph as it is, prune what they visited,
    then the reversed edges are merged by target. extra: their present neighbours stay candidates.
    Returns the number of distance computations of the searches."""
    out, far, comps = searched(graph, batch, degree, width, alpha, rule, keep_pruned, starts, extra)
    graph.nbrs[batch, :degree], graph.dists[batch, :degree] = out, far
    r, c = np.nonzero(out >= 0)
    used, nbrs, dists = merged_arrivals(graph, batch[r], out[r, c], far[r, c], degree, alpha, rule, keep_pruned)
    graph.nbrs[used], graph.dists[used] = nbrs, dists
    return comps


def draws(ids: np.ndarray, *parts) -> np.ndarray:
    """The draw of each id, with the parts before it (see draw_value)."""
    first = hashlib.md5((":".join(map(str, parts)) + ":").encode())
    out = np.empty(len(ids), dtype=np.int64)
    for i, x in enumerate(ids.tolist()):
        h = first.copy()
        h.update(b"%d" % x)
        out[i] = int.from_bytes(h.digest()[:4], "big")
    return out


def hashed_order(ids: np.ndarray, seed: int) -> np.ndarray:
    """Positions in the order of (draw of the id, id)."""
    return np.lexsort((ids, draws(ids, seed)))


def medoid(vecs: np.ndarray, metric: str = "l2") -> int:
    mean = np.round(vecs * (1 << 20)).sum(axis=1, keepdims=True) / (1 << 20) / max(1, vecs.shape[1])
    d = gathered(mean, np.zeros(vecs.shape[1], np.int64), vecs, np.arange(vecs.shape[1]), metric)
    return int(np.lexsort((np.arange(len(d)), d))[0]) if len(d) else 0


def build_alpha(
    vecs: np.ndarray, ids: np.ndarray, degree: int = 64, width: int = 128, alpha: float = 1.2, theta: float = 0.02,
    rule: str = "inclusive", start: str = "medoid", seed: int = 42, metric: str = "l2", graph: Graph | None = None,
) -> tuple[Graph, int]:
    """Incremental graph: growing batches, each against the snapshot the last one left."""
    n = len(ids)
    comps = 0
    order = hashed_order(ids, seed)
    first = medoid(vecs, metric) if start == "medoid" else int(order[0]) if n else 0
    extra = graph is not None
    if graph is None:
        graph = empty_graph(vecs, degree, first, metric)
    order = order[order != graph.start]
    cap = max(1, math.ceil(theta * n))
    for lo, hi in schedule(len(order), cap, rule):
        comps += insert_batch(graph, order[lo - 1: hi], degree, width, alpha, extra=extra)
    return graph, comps


def levels(ids: np.ndarray, m: int, seed: int, top: int | None = None) -> np.ndarray:
    """Highest layer of each id: geometric, by a hashed draw."""
    u = (draws(ids, seed, "level") + 1) / RANGE
    out = np.floor(-np.log(u) / math.log(m)).astype(np.int64) if len(ids) else np.zeros(0, np.int64)
    return out if top is None else np.minimum(out, top)


def build_layered(
    vecs: np.ndarray, ids: np.ndarray, m: int = 16, width: int = 128, alpha: float = 1.0, theta: float = 0.02,
    keep_pruned: bool = True, max_level: int | None = None, rule: str = "inclusive", seed: int = 42, metric: str = "l2",
) -> tuple[Graph, int]:
    """Nested layers of geometrically shrinking size, each an incremental graph; the bottom one has
    twice the degree. Layers above the bottom are kept as graphs over their own members."""
    n = len(ids)
    level = levels(ids, m, seed, max_level)
    bottom = empty_graph(vecs, 2 * m, 0, metric)
    if not n:
        return bottom, 0
    comps = 0
    bottom.entry = int(np.lexsort((np.arange(n), -level))[0])
    bottom.start = bottom.entry
    order = hashed_order(ids, seed)
    order = order[order != bottom.entry]
    graphs = [bottom] + [empty_graph(vecs, m, bottom.entry, metric) for _ in range(int(level.max()))]
    cap = max(1, math.ceil(theta * n))
    for lo, hi in schedule(len(order), cap, rule):
        batch = order[lo - 1: hi]
        comps += insert_layered(graphs, batch, level[batch], m, width, alpha, keep_pruned)
    for layer, graph in enumerate(graphs[1:], 1):
        bottom.upper.append({int(p): (graph.nbrs[p], graph.dists[p]) for p in np.flatnonzero(level >= layer)})
    return bottom, comps


def insert_layered(graphs: list[Graph], batch: np.ndarray, level: np.ndarray, m: int, width: int, alpha: float, keep_pruned: bool = True) -> int:
    """One batch into nested layers (the bottom first): each point goes down from the entry with beams of
    one, on the graphs as they are, and is inserted into the layers up to its level."""
    at, comps = np.full(len(batch), graphs[0].entry), 0
    entries: list[np.ndarray] = [at]
    for layer in range(len(graphs) - 1, 0, -1):  # the way down, on the snapshot before this batch
        found = beam_search(graphs[layer], graphs[layer].vecs.T[batch].T, 1, starts=at)
        at = found.nearest(1)[0][:, 0]
        entries.append(at)
        comps += int(found.comps.sum())
    entries.reverse()  # entries[l]: where a search in layer l begins
    for layer, graph in enumerate(graphs):
        mine = level >= layer
        if mine.any():
            comps += insert_batch(graph, batch[mine], 2 * m if layer == 0 else m, width, alpha, keep_pruned=keep_pruned, starts=entries[layer][mine])
    return comps


def insert_points(graph: Graph, ids: np.ndarray, fresh: np.ndarray, degree: int, width: int, alpha: float, m: int | None = None, seed: int = 42) -> int:
    """Insert the vertices at positions `fresh`, which have no edges yet, in growing batches; with m, into
    a layered graph. Returns the distances that the searches computed."""
    old, comps = graph.n - len(fresh), 0
    if not len(fresh):
        return 0
    cap, rule = max(1, old), "inclusive" if old else "doubling"
    if m is None:
        if not old:
            graph.start, fresh = int(fresh[0]), fresh[1:]
        for lo, hi in schedule(len(fresh), cap, rule):
            comps += insert_batch(graph, fresh[lo - 1: hi], degree, width, alpha)
        connect(graph)  # pruning for the arrivals may have cut vertices off
        return comps
    level = levels(ids, m, seed)
    graphs = [graph]
    for layer, rows in enumerate(graph.upper, 1):
        own = layer_graph(graph, layer, m)
        r, c = np.nonzero(own.nbrs >= 0)
        own.dists[r, c] = gathered(graph.vecs, r, graph.vecs, own.nbrs[r, c], graph.metric)
        graphs.append(own)
        level[list(rows)] = np.maximum(level[list(rows)], layer)
    had = np.setdiff1d(np.arange(graph.n), fresh)
    level[had] = np.minimum(level[had], len(graph.upper))  # an old vertex keeps its layers
    top = fresh[np.lexsort((fresh, -level[fresh]))[0]]
    if not old or level[top] > len(graph.upper):  # a new entry, alone in the layers above
        if old:
            comps += insert_layered(graphs, np.array([top]), np.array([len(graph.upper)]), m, width, alpha)
        graph.start = graph.entry = int(top)
        graphs += [empty_graph(graph.vecs, m, int(top), graph.metric) for _ in range(len(graphs) - 1, int(level[top]))]
        fresh = fresh[fresh != top]
    for lo, hi in schedule(len(fresh), cap, rule):
        batch = fresh[lo - 1: hi]
        comps += insert_layered(graphs, batch, level[batch], m, width, alpha)
    graph.upper = [{int(p): (g.nbrs[p], g.dists[p]) for p in np.flatnonzero(level >= layer)} for layer, g in enumerate(graphs[1:], 1)]
    return comps


def layer_graph(graph: Graph, layer: int, degree: int = 1) -> Graph:
    """One layer above the bottom as a graph of its own."""
    rows = graph.upper[layer - 1]
    width = max([degree, *(len(x) for x, _ in rows.values())])
    out = empty_graph(graph.vecs, width, graph.entry, graph.metric)
    for p, (x, d) in rows.items():
        out.nbrs[p, : len(x)], out.dists[p, : len(x)] = x, d
    return out


def layered_search(graph: Graph, queries: np.ndarray, width: int, k: int = 1, eps: float | None = None, visited: str = "seen", keep: int | None = None) -> Found:
    """From the entry down with beams of one, then a full beam at the bottom; with keep, one that holds every
    vertex, of which the `keep` nearest are returned."""
    at = np.full(queries.shape[1], graph.entry)
    comps = np.zeros(queries.shape[1], np.int64)
    for layer in range(len(graph.upper), 0, -1):
        found = beam_search(layer_graph(graph, layer), queries, 1, starts=at)
        at = found.nearest(1)[0][:, 0]
        comps += found.comps
    found = exhausted(graph, queries, keep, at) if keep is not None else beam_search(graph, queries, width, k, eps, visited, starts=at)
    found.comps = found.comps + comps
    return found


def tree_leaves(vecs: np.ndarray, ids: np.ndarray, leaf: int, tree: int = 0, kind: str = "pivots", seed: int = 42, metric: str = "l2", root: str = "") -> list[tuple[str, np.ndarray]]:
    """(path, positions) of the leaves of a random cluster tree, or of what is below its node `root`. kind "pivots": members go to the
    nearer of two drawn members; "hyperplane": to a side of the plane with a drawn normal through
    the middle of the two members' projections. A node whose points cannot be told apart is cut in halves."""
    vecs = np.asfortranarray(vecs)
    out, todo = [], [(root, np.arange(len(ids)))]
    while todo:
        path, own = todo.pop()
        if len(own) <= max(1, leaf):
            out.append((path, own))
            continue
        drawn = draws(ids[own], seed, tree, path)
        a = own[drawn.argmin()]  # positions are in the order of ids
        other = (vecs.T[own] != vecs.T[a]).any(axis=1)
        b = own[np.where(other, drawn, RANGE).argmin()] if other.any() else None
        if b is None:
            sides = np.ones(len(own), dtype=bool)
            sides[np.lexsort((own, drawn))[: len(own) // 2]] = False
        elif kind == "pivots":
            da = gathered(vecs, np.array([a]), vecs, own, metric)
            db = gathered(vecs, np.array([b]), vecs, own, metric)
            sides = da > db
        else:
            normal = np.array([1.0 if draw_value(seed, tree, path, "dim", j) & 1 else -1.0 for j in range(len(vecs))])
            side = np.zeros(len(own))
            for w, row in zip(normal, vecs, strict=True):
                side += w * row[own]
            cut = (side[own == a][0] + side[own == b][0]) / 2.0
            sides = side > cut
            if sides.all() or not sides.any():
                rank = np.lexsort((own, side))
                sides = np.zeros(len(own), dtype=bool)
                sides[rank[len(own) // 2:]] = True
        todo += [(path + "1", own[sides]), (path + "0", own[~sides])]
    return sorted(out, key=lambda x: x[0])


def leaf_mst(vecs: np.ndarray, own: np.ndarray, near: int | None = 10, max_degree: int = 3, metric: str = "l2") -> list[tuple[int, int, float]]:
    """Edges of a spanning forest with bounded degree over the points `own`: candidate edges (each
    point's `near` nearest, or all pairs) by (distance, lower id, higher id)."""
    m = len(own)
    if m < 2:
        return []
    d = gathered(vecs, own[:, None], vecs, own[None, :], metric)
    if near is None or near >= m - 1:
        i, j = np.triu_indices(m, 1)
    else:
        e = d.copy()
        e[np.arange(m), np.arange(m)] = np.inf
        close = np.lexsort((np.broadcast_to(np.arange(m), e.shape), e), axis=1)[:, :near]
        i, j = np.repeat(np.arange(m), near), close.reshape(-1)
        pairs = np.unique(np.stack([np.minimum(i, j), np.maximum(i, j)]), axis=1)
        i, j = pairs
    order = np.lexsort((j, i, d[i, j]))
    root, degree, out = list(range(m)), [0] * m, []

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for e in order.tolist():
        a, b = int(i[e]), int(j[e])
        if degree[a] < max_degree and degree[b] < max_degree:
            ra, rb = find(a), find(b)
            if ra != rb:
                root[max(ra, rb)] = min(ra, rb)
                degree[a] += 1
                degree[b] += 1
                out.append((int(own[a]), int(own[b]), float(d[a, b])))
                if len(out) == m - 1:
                    break
    return out


def leaf_neighbours(vecs: np.ndarray, own: np.ndarray, k: int, metric: str = "l2") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Directed edges (source, target, distance) to each point's k nearest within `own`."""
    m = len(own)
    if m < 2:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    d = gathered(vecs, own[:, None], vecs, own[None, :], metric)
    d[np.arange(m), np.arange(m)] = np.inf
    k = min(k, m - 1)
    close = np.lexsort((np.broadcast_to(np.arange(m), d.shape), d), axis=1)[:, :k]
    return np.repeat(own, k), own[close.reshape(-1)], np.take_along_axis(d, close, axis=1).reshape(-1)


def from_edges(vecs: np.ndarray, src: np.ndarray, dst: np.ndarray, dist: np.ndarray, degree: int, alpha: float | None, metric: str = "l2", start: int = 0) -> Graph:
    """A graph of the distinct edges, each list cut to `degree`: by the alpha rule, or, with alpha
    None, to the nearest."""
    graph = empty_graph(vecs, degree, start, metric)
    real = src != dst
    src, dst, dist = src[real], dst[real], dist[real]
    if not len(src):
        return graph
    order = np.lexsort((dst, src))
    src, dst, dist = src[order], dst[order], dist[order]
    one = np.ones(len(src), dtype=bool)
    one[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
    src, dst, dist = src[one], dst[one], dist[one]
    used, first, many = np.unique(src, return_index=True, return_counts=True)
    by_size = np.argsort(many, kind="stable")  # lists of about one length share a table, so that hubs do not widen others'
    lo = 0
    while lo < len(used):
        hi = lo + 1
        while hi < len(used) and hi - lo < 4096 and (hi - lo + 1) * many[by_size[hi]] <= 1 << 20:
            hi += 1
        rows = by_size[lo:hi]
        own, n, lo = used[rows], many[rows], hi
        cand = np.full((len(rows), int(n.max())), -1, dtype=np.int64)
        far = np.full(cand.shape, np.inf)
        row = np.repeat(np.arange(len(rows)), n)
        col = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        at = np.repeat(first[rows], n) + col
        cand[row, col], far[row, col] = dst[at], dist[at]
        graph.nbrs[own], graph.dists[own] = prune(graph.vecs, own, cand, far, degree, alpha or 1.0, "alpha" if alpha else "nearest", metric)
    return graph


def build_tree_mst(
    vecs: np.ndarray, ids: np.ndarray, trees: int = 30, leaf: int = 1000, near: int | None = 10, max_degree: int = 3,
    degree: int = 64, alpha: float = 1.0, seed: int = 42, metric: str = "l2",
) -> Graph:
    vecs = np.asfortranarray(vecs)
    edges, comps = [], 0
    for t in range(trees):
        for path, own in tree_leaves(vecs, ids, leaf, t, "pivots", seed, metric):
            edges += leaf_mst(vecs, own, near, max_degree, metric)
            comps += 2 * len(path) * len(own) + len(own) * (len(own) - 1) // 2
    a = np.array([e[0] for e in edges], dtype=np.int64)
    b = np.array([e[1] for e in edges], dtype=np.int64)
    d = np.array([e[2] for e in edges])
    graph = from_edges(vecs, np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([d, d]), degree, alpha, metric, medoid(vecs, metric))
    graph.comps = comps
    return graph


def undirected(src, dst, dist, cap: int | None, ids: np.ndarray, seed: int, rnd: int):
    """Edges and their opposites; a vertex beyond `cap` keeps those with the least draws."""
    s, t, d = np.concatenate([src, dst]), np.concatenate([dst, src]), np.concatenate([dist, dist])
    key = np.unique(s * max(1, len(ids)) + t, return_index=True)[1]
    s, t, d = s[key], t[key], d[key]
    if cap is None or (np.bincount(s).max() if len(s) else 0) <= cap:
        return s, t, d
    keep = np.bincount(s)[s] <= cap
    for x in np.unique(s[~keep]):  # s is in order, as the keys are
        own = np.arange(*np.searchsorted(s, (x, x + 1)))
        keep[own[np.lexsort((t[own], draws(ids[t[own]], seed, rnd, int(ids[x]))))[:cap]]] = True
    return s[keep], t[keep], d[keep]


def descent_round(vecs, src, dst, dist, k: int, cap: int | None, ids, seed: int, rnd: int, metric: str = "l2", block: int = 512, known: np.ndarray | None = None):
    """One round of neighbour descent; returns the new edges and how many were not there before.

    Two-hop sets are made for `block` sources at a time. known: codes (source * n + target) of the edges
    of the round before; where no cap cut that round or this one, a two-hop way of known edges was
    looked at then, and is left out now, which changes nothing."""
    n = vecs.shape[1]
    vecs = np.asfortranarray(vecs)
    s, t, d = undirected(src, dst, dist, cap, ids, seed, rnd)
    order = np.lexsort((t, s))
    s, t = s[order], t[order]
    begin = np.searchsorted(s, np.arange(n + 1))
    deg = np.diff(begin)
    old = np.unique(src * n + dst)
    kth = np.full(n, -np.inf)  # of a full list: what is beyond its last edge does not enter it
    np.maximum.at(kth, src, dist)
    kth[np.bincount(src, minlength=n) < k] = np.inf
    fresh = np.ones(len(s), dtype=bool)
    if known is not None and len(s) and (cap is None or deg.max() < cap):
        fresh = ~(np.isin(s * n + t, known) | np.isin(t * n + s, known))
    out_s, out_t, out_d, spent = [], [], [], 0
    for lo in range(0, n, block):
        hi = min(lo + block, n)
        one = slice(begin[lo], begin[hi])
        hs, hm = s[one], t[one]
        many = deg[hm]
        at = np.repeat(begin[hm], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        way = np.repeat(fresh[one], many) | fresh[at]
        hop_s, hop_t = np.repeat(hs, many)[way], t[at[way]]
        mine = (src >= lo) & (src < hi)
        have = np.sort(src[mine] * n + dst[mine])
        pairs = np.sort(np.concatenate([hop_s * n + hop_t, hs * n + hm]))
        pairs = pairs[np.diff(pairs, prepend=-1) > 0]
        pairs = pairs[~np.isin(pairs, have, assume_unique=True)]
        a, b = pairs // n, pairs % n
        a, b = a[a != b], b[a != b]
        spent += len(a)
        far = gathered(vecs, a, vecs, b, metric, kth[a])
        near = np.isfinite(far) | ~np.isfinite(kth[a])
        a, b, far = a[near], b[near], np.concatenate([far[near], dist[mine]])
        a, b = np.concatenate([a, src[mine]]), np.concatenate([b, dst[mine]])
        best = np.lexsort((b, far, a))
        a, b, far = a[best], b[best], far[best]
        keep = np.arange(len(a)) - np.searchsorted(a, a, side="left") < k
        out_s.append(a[keep])
        out_t.append(b[keep])
        out_d.append(far[keep])
    ns, nt, nd = np.concatenate(out_s), np.concatenate(out_t), np.concatenate(out_d)
    changed = int((~np.isin(ns * n + nt, old)).sum())
    return ns, nt, nd, changed, spent


def build_descent(
    vecs: np.ndarray, ids: np.ndarray, trees: int = 10, leaf: int = 100, k: int = 40, degree: int = 64, alpha: float = 1.2,
    cap: int | None = 2000, delta: float = 0.001, max_rounds: int = 20, init: str = "trees", seed: int = 42, metric: str = "l2", block: int = 512,
) -> tuple[Graph, int]:
    n, comps = len(ids), 0
    vecs = np.asfortranarray(vecs)
    parts = []
    if init == "trees":
        for t in range(trees):
            for path, own in tree_leaves(vecs, ids, leaf, t, "hyperplane", seed, metric):
                parts.append(leaf_neighbours(vecs, own, k, metric))
                comps += 2 * len(path) + len(own) * (len(own) - 1) // 2
    else:  # k draws of positions for every point
        for i in range(n):
            o = np.unique(draws(np.arange(k), seed, int(ids[i])) % n)
            o = o[o != i]
            parts.append((np.full(len(o), i), o, gathered(vecs, np.full(len(o), i), vecs, o, metric)))
            comps += len(o)
    src, dst, dist = (np.concatenate([p[i] for p in parts]) for i in range(3)) if parts else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
    start = from_edges(vecs, src, dst, dist, k, None, metric)
    r, c = np.nonzero(start.nbrs >= 0)
    src, dst, dist = r, start.nbrs[r, c], start.dists[r, c]
    rounds, known = 0, None
    while rounds < max_rounds and len(src):
        before = src * n + dst
        whole = cap is None or np.bincount(np.concatenate([src, dst]), minlength=n).max() < cap
        src, dst, dist, changed, spent = descent_round(vecs, src, dst, dist, k, cap, ids, seed, rounds, metric, block, known)
        known = np.unique(before) if whole else None
        rounds += 1
        comps += spent
        if changed <= delta * n * k:
            break
    # nearest-neighbour lists point one way only; with their opposites the graph can be walked
    s, t, d = undirected(src, dst, dist, None, ids, seed, 0)
    graph = from_edges(vecs, s, t, d, degree, alpha, metric, medoid(vecs, metric))
    graph.comps = comps
    return graph, rounds


def connect(graph: Graph, width: int = 32) -> None:
    """Make every vertex reachable from the start: each group that cannot be reached is searched for, and
    the nearest vertex met that has a free place gets an edge to it (the tables grow if none has)."""
    covered = reach(graph)
    roots = []
    for p in np.flatnonzero(~covered).tolist():
        if covered[p]:
            continue
        roots.append(p)
        front = np.array([p])
        while len(front):
            covered[front] = True
            near = np.unique(graph.nbrs[front])
            near = near[near >= 0]
            front = near[~covered[near]]
    if not roots:
        return
    lost = np.array(roots)
    found = beam_search(graph, graph.vecs.T[lost].T, width)
    at, far = found.nearest(found.visited.shape[1])
    for p, ids, dist in zip(roots, at, far, strict=True):
        met = np.flatnonzero((ids >= 0) & np.isfinite(dist))
        free = met[(graph.nbrs[ids[met]] < 0).any(axis=1)]
        if not len(free):
            graph.nbrs = np.pad(graph.nbrs, ((0, 0), (0, 1)), constant_values=-1)
            graph.dists = np.pad(graph.dists, ((0, 0), (0, 1)), constant_values=np.inf)
            free = met
        v, d = int(ids[free[0]]), float(dist[free[0]])
        for a, b in ((v, p), (p, v)):
            spare = np.flatnonzero(graph.nbrs[a] < 0)
            if len(spare) and not (graph.nbrs[a] == b).any():
                graph.nbrs[a, spare[0]], graph.dists[a, spare[0]] = b, d


def reach(graph: Graph, start: int | None = None) -> np.ndarray:
    """Which positions can be reached from the start, or from the graph's own."""
    seen = np.zeros(graph.n, dtype=bool)
    front = np.array([graph.start if start is None else start]) if graph.n else np.empty(0, np.int64)
    while len(front):
        seen[front] = True
        near = np.unique(graph.nbrs[front])
        near = near[near >= 0]
        front = near[~seen[near]]
    return seen


def reaching(graph: Graph, end: int) -> np.ndarray:
    """Which positions the given one can be reached from."""
    row, col = np.nonzero(graph.nbrs >= 0)
    dst = graph.nbrs[row, col]
    seen = np.zeros(graph.n, dtype=bool)
    fresh = np.array([end])
    while len(fresh):
        seen[fresh] = True
        fresh = np.unique(row[seen[dst] & ~seen[row]])
    return seen


def exhausted(graph: Graph, queries: np.ndarray, keep: int | None = None, starts: np.ndarray | None = None, radius: float | None = None) -> Found:
    """What beam_search gives with a beam that holds every vertex and no eps: each query then processes all
    that its start reaches, at one distance a vertex. So what is reached is found once for the starts that
    reach each other, and scanned in blocks; of it, the `keep` nearest or all within radius are returned."""
    b = queries.shape[1]
    own = starts if starts is not None else np.full(b, graph.start)
    size = np.zeros(b, np.int64)
    rows, ids, far = [], [], []
    left = np.unique(own)
    while len(left):
        seen = reach(graph, left[0])
        alike = seen[left] & reaching(graph, left[0])[left] if len(left) > 1 else np.ones(1, dtype=bool)
        at, who = np.flatnonzero(seen), np.flatnonzero(np.isin(own, left[alike]))
        x = graph.vecs.T[at]
        step = max(8, (32 << 20) // max(1, len(at)))
        for lo in range(0, len(who), step):
            r, c, d = close_pairs(queries.T[who[lo: lo + step]], x, graph.metric, None if keep is None else min(keep, len(at)), radius)
            order = np.lexsort((c, d, r))
            r, c, d = r[order], c[order], d[order]
            if keep is not None:
                first = np.arange(len(r)) - np.searchsorted(r, r, side="left") < keep
                r, c, d = r[first], c[first], d[first]
            rows.append(who[lo: lo + step][r])
            ids.append(at[c])
            far.append(d)
        size[who] = len(at)
        left = left[~alike]
    r, p, d = (np.concatenate(x) if x else np.empty(0, t) for x, t in ((rows, np.int64), (ids, np.int64), (far, float)))
    order = np.argsort(r, kind="stable")
    r, p, d = r[order], p[order], d[order]
    place = np.arange(len(r)) - np.searchsorted(r, r, side="left")
    most = int(place.max()) + 1 if len(r) else 0
    out, dist = np.full((b, most), -1, dtype=np.int64), np.full((b, most), np.inf)
    out[r, place], dist[r, place] = p, d
    return Found(out, dist, size, size.copy(), out, dist, size)
