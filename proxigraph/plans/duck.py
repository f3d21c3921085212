"""Pieces of DuckDB SQL that the oracle queries are put together from."""

from __future__ import annotations

from proxigraph.functions.prng import draw_sql

EMB = "p AS (SELECT vec_id AS id, embedding AS vec FROM embeddings WHERE vec_id % 10 <> 0), q AS (SELECT vec_id AS qid, embedding AS qvec FROM embeddings WHERE vec_id % 10 = 0)"
INT8 = "list_transform(embedding, lambda x: greatest(-127, least(127, round(x::double * 127.0::double)))::tinyint)"


def fold(terms: str) -> str:
    return f"list_reduce({terms}, lambda x, y: x + y, 0.0::double)"


def l2(a: str, b: str) -> str:
    return "sqrt(" + fold(f"list_transform(list_zip({a}, {b}), lambda z: (z[1]::double - z[2]::double) * (z[1]::double - z[2]::double))") + ")"


def dot(a: str, b: str) -> str:
    return fold(f"list_transform(list_zip({a}, {b}), lambda z: z[1]::double * z[2]::double)")


def norm(a: str) -> str:
    return "sqrt(" + fold(f"list_transform({a}, lambda z: z::double * z::double)") + ")"


def cosine(a: str, b: str) -> str:
    return f"(1.0::double - {dot(a, b)} / ({norm(b)} * {norm(a)}))"


def knn(ctes: str, dist: str, k: int = 10, where: str = "TRUE") -> str:
    """The k nearest points p of each query q, rounded."""
    return f"""WITH {ctes}, met AS (SELECT qid, id, {dist} AS dist FROM p, q WHERE {where}),
    top AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM met)
    SELECT qid, id, round(dist, 6) AS dist, rank FROM top WHERE rank <= {k}"""


def counts(text: str, dims: int = 128) -> str:
    """Hashed token counts of a text column."""
    buckets = f"list_transform(list_filter(string_split(lower(coalesce({text}, '')), ' '), lambda t: t <> ''), lambda t: ('0x' || substr(md5(t), 1, 8))::bigint % {dims})"
    return f"(SELECT list_transform(range({dims}), lambda i: least(255, len(list_filter(b, lambda x: x = i)))) FROM (SELECT {buckets} AS b))"


#: All points.
WHOLE = "p AS (SELECT vec_id AS id, embedding AS vec FROM embeddings)"


def graph(k: int, points: str = "p", name: str = "g") -> str:
    """(src, dst, dist): exact k-NN graph over the points."""
    return f"{name} AS (SELECT a.id AS src, b.id AS dst, {l2('b.vec', 'a.vec')} AS dist FROM {points} a, {points} b WHERE a.id <> b.id QUALIFY row_number() OVER (PARTITION BY a.id ORDER BY dist, b.id) <= {k})"


def pruned(cand: str, degree: int, alpha: float, points: str = "p", name: str = "pr") -> str:
    """Recursive CTEs that prune (src, dst, dist) by the alpha rule; the rows are in {name}."""
    return f"""{name}_l AS (SELECT src, list(struct_pack(dist := dist, id := dst, vec := vec) ORDER BY dist, dst) AS rem FROM {cand} JOIN {points} ON id = dst GROUP BY src),
    {name}_r(src, kept, rem) AS (
      SELECT src, []::struct(id bigint, dist double)[], rem FROM {name}_l
      UNION ALL
      SELECT src, list_append(kept, struct_pack(id := rem[1].id, dist := rem[1].dist)),
             list_filter(rem[2:], lambda x: {alpha}::double * {l2('rem[1].vec', 'x.vec')} > x.dist)
      FROM {name}_r WHERE len(rem) > 0 AND len(kept) < {degree}),
    {name} AS (SELECT src, e.id AS dst, e.dist AS dist FROM (SELECT src, unnest(kept) AS e FROM {name}_r WHERE len(rem) = 0 OR len(kept) = {degree}))"""


def beam(ctes: str, width: int, start: int | str, k: int = 10, eps: float | None = None) -> str:
    """Recursive CTEs of beam search over g(src, dst) and p from `start`; final states in `fin`."""
    live = "len(list_filter(beam, lambda e: NOT e.done)) > 0"
    if eps is not None:
        live += f" AND (len(beam) < {k} OR list_filter(beam, lambda e: NOT e.done)[1].dist <= {1 + eps}::double * beam[{k}].dist)"
    return f"""WITH RECURSIVE {ctes},
    r(qid, qvec, beam, log, comps) AS (
      SELECT qid, qvec, [struct_pack(dist := {l2('p.vec', 'qvec')}, id := p.id, done := false)], []::struct(dist double, id bigint)[], 1::bigint FROM q, p WHERE p.id = {start}
      UNION ALL
      SELECT qid, qvec, list_sort(list_concat(marked, new))[1:{width}], list_append(log, struct_pack(dist := pick.dist, id := pick.id)), comps + len(new) FROM (
        SELECT qid, qvec, log, comps, pick, marked,
               coalesce((SELECT list(struct_pack(dist := {l2('p.vec', 's.qvec')}, id := p.id, done := false)) FROM g JOIN p ON p.id = g.dst
                         WHERE g.src = s.pick.id AND NOT list_contains(s.inside, g.dst) AND NOT list_contains(s.past, g.dst)), []) AS new
        FROM (SELECT qid, qvec, log, comps, list_filter(beam, lambda e: NOT e.done)[1] AS pick,
                     list_transform(beam, lambda e: struct_pack(dist := e.dist, id := e.id, done := e.done OR e.id = list_filter(beam, lambda f: NOT f.done)[1].id)) AS marked,
                     list_transform(beam, lambda e: e.id) AS inside, list_transform(log, lambda e: e.id) AS past
              FROM r WHERE {live}) s)),
    fin AS (SELECT * FROM r WHERE NOT ({live}))"""


def first_cells(k: int, points: str = "p", seed: int = 42) -> str:
    return f"c0 AS (SELECT row_number() OVER (ORDER BY {draw_sql(seed, 'id')}, id) - 1 AS cell, vec::double[] AS centroid FROM {points} QUALIFY cell < {k})"


def cell_steps(iters: int, points: str = "p") -> str:
    """c1 ... c{iters}: k-means steps with fixed-point means."""
    out = []
    for i in range(iters):
        out.append(f"""a{i} AS (SELECT id, vec, cell FROM (SELECT id, vec, cell, {l2('centroid', 'vec')} AS dist FROM {points}, c{i}) QUALIFY row_number() OVER (PARTITION BY id ORDER BY dist, cell) = 1),
        m{i} AS (SELECT cell, j, sum(round(vec[j]::double * 1048576)::hugeint)::double / 1048576 / count(*) AS x FROM a{i}, unnest(range(1, len(vec) + 1)) t(j) GROUP BY cell, j),
        v{i} AS (SELECT cell, list(x ORDER BY j) AS fresh FROM m{i} GROUP BY cell),
        c{i + 1} AS (SELECT cell, coalesce(fresh, centroid) AS centroid FROM c{i} LEFT JOIN v{i} USING (cell))""")
    return ", ".join(out)


def descent(rounds: int, k: int, cap: int, points: str = "p", seed: int = 42) -> str:
    """g0 must be there; g1 ... g{rounds}: rounds of neighbour descent."""
    out = []
    for i in range(rounds):
        out.append(f"""u{i} AS (SELECT src, dst FROM (SELECT src, dst FROM g{i} UNION SELECT dst, src FROM g{i}) QUALIFY row_number() OVER (PARTITION BY src ORDER BY {draw_sql(seed, str(i), 'src', 'dst')}, dst) <= {cap}),
        h{i} AS (SELECT a.src, b.dst FROM u{i} a JOIN u{i} b ON a.dst = b.src UNION SELECT src, dst FROM u{i} UNION SELECT src, dst FROM g{i}),
        g{i + 1} AS (SELECT src, dst, {l2('x.vec', 'y.vec')} AS dist FROM h{i} JOIN {points} x ON x.id = src JOIN {points} y ON y.id = dst WHERE src <> dst
                     QUALIFY row_number() OVER (PARTITION BY src ORDER BY dist, dst) <= {k})""")
    return ", ".join(out)
