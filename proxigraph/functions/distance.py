"""Distances: SQL expressions over array columns, and numpy blocks with the same bits.

Every sum is a left fold over the components in double precision. The expressions below, the blocks,
and a left fold in other engines therefore give equal bits, which exact tests rely on; pairwise or
blocked summation would not.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2", "cosine", "ip")


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _fold(terms: Column, start: str = "double") -> Column:
    return F.aggregate(terms, F.lit(0).cast(start), lambda acc, x: acc + x)


def _product(a: Column, b: Column) -> Column:
    return _fold(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def l2_sq(a: Column | str, b: Column | str) -> Column:
    return _fold(F.zip_with(_c(a), _c(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))))


def l2(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(l2_sq(a, b))


def l2_sq_int(a: Column | str, b: Column | str) -> Column:
    """Exact squared distance of integer vectors."""
    return _fold(F.zip_with(_c(a), _c(b), lambda x, y: (x.cast("long") - y.cast("long")) * (x.cast("long") - y.cast("long"))), "long")


def dot(a: Column | str, b: Column | str) -> Column:
    return _product(_c(a), _c(b))


def norm(a: Column | str) -> Column:
    return F.sqrt(_product(_c(a), _c(a)))


def cosine(a: Column | str, b: Column | str) -> Column:
    """1 - cos of the angle; null if a vector is zero."""
    size = norm(a) * norm(b)
    return F.when(size > 0, F.lit(1.0) - dot(a, b) / size)


def neg_ip(a: Column | str, b: Column | str) -> Column:
    return -dot(a, b)


def expression(metric: str, a: Column | str, b: Column | str) -> Column:
    return {"l2": l2, "cosine": cosine, "ip": neg_ip}[metric](a, b)


def block(q: np.ndarray, x: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Distances of every row of q to every row of x, one dimension after the other."""
    qt, xt = np.ascontiguousarray(q.T, dtype=np.float64), np.ascontiguousarray(x.T, dtype=np.float64)
    acc = np.zeros((q.shape[0], x.shape[0]))
    if metric == "l2":
        for a, b in zip(qt, xt, strict=True):
            t = a[:, None] - b[None, :]
            acc += t * t
        return np.sqrt(acc)
    for a, b in zip(qt, xt, strict=True):
        acc += a[:, None] * b[None, :]
    if metric == "ip":
        return -acc
    size = np.sqrt(squares(qt))[:, None] * np.sqrt(squares(xt))[None, :]
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(size > 0, 1.0 - acc / size, np.nan)


def squares(by_dim: np.ndarray) -> np.ndarray:
    acc = np.zeros(by_dim.shape[1])
    for a in by_dim:
        acc += a * a
    return acc


#: Components that `gathered` holds at once, so that they stay in the cache.
_CHUNK = 1 << 16


def gathered(by_dim: np.ndarray, left: np.ndarray, right_by_dim: np.ndarray, right: np.ndarray, metric: str = "l2", most: np.ndarray | None = None) -> np.ndarray:
    """Distances of by_dim[:, left] to right_by_dim[:, right]; index arrays broadcast. Vectors are
    given by dimension; the transpose of contiguous rows is fastest. Sums are running sums along a
    vector, which is the left fold. most, of each pair of one-dimensional index arrays: a distance beyond
    it may be given as infinite (l2 only); a sum in any order, with room for its rounding, tells these."""
    if left.ndim == 2 and left.shape[1] == 1 and right.shape[0] == 1:
        return np.where(np.isnan(d := block(by_dim.T[left[:, 0]], right_by_dim.T[right[0]], metric)), np.inf, d)
    left, right = np.broadcast_arrays(left, right)
    q, x = np.ascontiguousarray(by_dim.T), np.ascontiguousarray(right_by_dim.T)
    out = np.empty(left.shape)
    if not q.shape[1]:
        out[:] = 0.0
        return out
    step = max(1, _CHUNK // q.shape[1])
    top = None if most is None or metric != "l2" else most * most * (1 + 1e-9) + 1e-300
    for lo in range(0, len(left), step):
        t = x.take(right[lo: lo + step], axis=0)
        if metric == "l2":
            t -= q.take(left[lo: lo + step], axis=0)
            if top is not None:
                near = np.flatnonzero(~(np.einsum("ij,ij->i", t, t) > top[lo: lo + step]))
                out[lo: lo + step] = np.inf
                t = t[near]
                t *= t
                out[lo + near] = np.add.accumulate(t, axis=1, out=t)[:, -1]
                continue
            t *= t
        else:
            t *= q.take(left[lo: lo + step], axis=0)
        out[lo: lo + step] = np.add.accumulate(t, axis=1, out=t)[:, -1]
    if metric == "l2":
        return np.sqrt(out, out=out)
    out += 0.0  # a fold from zero has no negative zero
    if metric == "ip":
        return -out
    size = np.sqrt(squares(by_dim))[left] * np.sqrt(squares(right_by_dim))[right]
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(size > 0, 1.0 - out / size, np.inf)


def close_pairs(q: np.ndarray, x: np.ndarray, metric: str = "l2", k: int | None = None, radius: float | None = None, skip: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of x, distance) of all pairs that can be among the k nearest of a row of q, ties
    included, or of all within radius. A matrix product finds the candidates, with room for its
    rounding; only these get the exact left fold. skip: pairs to leave out (boolean matrix)."""
    q, x = np.ascontiguousarray(q, dtype=np.float64), np.ascontiguousarray(x, dtype=np.float64)
    if not len(q) or not len(x):
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    rough = q @ x.T
    qq, xx = np.einsum("ij,ij->i", q, q), np.einsum("ij,ij->i", x, x)
    with np.errstate(divide="ignore", invalid="ignore"):
        if metric == "l2":
            rough = qq[:, None] + xx[None, :] - 2 * rough
            room = 1e-9 * (qq + xx.max())
        elif metric == "ip":
            rough = -rough
            room = 1e-9 * np.sqrt(qq * xx.max())
        else:
            rough = 1.0 - rough / np.sqrt(qq[:, None] * xx[None, :])
            room = np.full(len(q), 1e-9)
    rough = np.where(np.isnan(rough), np.inf, rough)
    if skip is not None:
        rough[skip] = np.inf
    if radius is not None:
        least = np.full(len(q), radius * abs(radius) if metric == "l2" else radius)
    elif rough.shape[1] > k:
        least = np.partition(rough, k - 1, axis=1)[:, k - 1]
    else:
        least = np.full(len(q), np.finfo(float).max)
    r, c = np.nonzero((rough <= (least + room)[:, None]) & np.isfinite(rough))
    d = gathered(q.T, r, x.T, c, metric)
    keep = np.isfinite(d) if radius is None else d <= radius
    return r[keep], c[keep], d[keep]


def nearest_rows(q: np.ndarray, x: np.ndarray, k: int = 1, metric: str = "l2") -> tuple[np.ndarray, np.ndarray]:
    """Of each row of q the k nearest rows of x (all, if fewer) by (distance, row), and the distances;
    rows without a distance, as zero vectors under cosine, get the first rows at infinity."""
    k = min(k, len(x))
    r, c, d = close_pairs(q, x, metric, k)
    order = np.lexsort((c, d, r))
    r, c, d = r[order], c[order], d[order]
    place = np.arange(len(r)) - np.searchsorted(r, r, side="left")
    own = place < k
    out, far = np.tile(np.arange(k), (len(q), 1)), np.full((len(q), k), np.inf)
    out[r[own], place[own]], far[r[own], place[own]] = c[own], d[own]
    return out, far
