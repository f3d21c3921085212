"""Plain loops over dicts and lists, independent of the kernels, for graphs of a few dozen points."""

import math


def dist(a, b):
    acc = 0.0
    for x, y in zip(a, b, strict=True):
        acc += (x - y) * (x - y)
    return math.sqrt(acc)


def search(vecs, out, query, start, width):
    beam = [(dist(vecs[start], query), start)]
    visited = []
    comps = 1
    while True:
        todo = [e for e in beam if e[1] not in {v for _, v in visited}]
        if not todo:
            return visited, comps
        nearest = min(todo)
        visited.append(nearest)
        known = {v for _, v in beam} | {v for _, v in visited}
        for n in out.get(nearest[1], []):
            if n not in known:
                comps += 1
                beam.append((dist(vecs[n], query), n))
        beam = sorted(beam)[:width]


def prune(vecs, p, candidates, degree, alpha):
    left = sorted({(dist(vecs[p], vecs[c]), c) for c in candidates if c != p})
    kept = []
    while left and len(kept) < degree:
        d, c = left.pop(0)
        kept.append(c)
        left = [(e, x) for e, x in left if alpha * dist(vecs[c], vecs[x]) > e]
    return kept


def build(vecs, order, start, batches, degree, width, alpha):
    out = {start: []}
    for lo, hi in batches:
        batch = order[lo - 1: hi]
        snapshot = {k: list(v) for k, v in out.items()}
        new = {}
        for p in batch:
            visited, _ = search(vecs, snapshot, vecs[p], start, width)
            new[p] = prune(vecs, p, [v for _, v in visited], degree, alpha)
        out.update(new)
        arrivals = {}
        for p, targets in new.items():
            for t in targets:
                arrivals.setdefault(t, []).append(p)
        for t, came in arrivals.items():
            merged = list(dict.fromkeys(out[t] + came))
            out[t] = prune(vecs, t, merged, degree, alpha) if len(merged) > degree else merged
    return {k: set(v) for k, v in out.items()}


def descent_round(vecs, out, k):
    both = {p: set() for p in vecs}
    for p, targets in out.items():
        for t in targets:
            both[p].add(t)
            both[t].add(p)
    new = {}
    for p in vecs:
        cand = set(both[p]) | set(out.get(p, ()))
        for m in both[p]:
            cand |= both[m]
        cand.discard(p)
        new[p] = {c for _, c in sorted((dist(vecs[p], vecs[c]), c) for c in cand)[:k]}
    return new


def prim(vecs):
    names = sorted(vecs)
    seen, total = {names[0]}, 0.0
    while len(seen) < len(names):
        d, n = min((dist(vecs[a], vecs[b]), b) for a in seen for b in names if b not in seen)
        seen.add(n)
        total += d
    return total
