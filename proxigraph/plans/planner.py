"""Choices that need figures of the data: which engine, how many shards, which metric."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from proxigraph.operators.index import BUILDERS, GraphIndex
from proxigraph.operators.model import SHARD_ROWS, PointSet


@dataclass(frozen=True)
class Choice:
    engine: str  # "kernel", "batches", "rounds" or "sharded"
    shards: int
    reason: str


#: Points whose vectors and lists a worker has room for.
WORKER_ROWS = 4_000_000


def choose_engine(points: PointSet, shard_rows: int = SHARD_ROWS, whole: bool = False) -> Choice:
    """One task, if the points fit; else shards, or, where one graph over all points is wanted, all tasks
    together, with the graph in every worker or in joins."""
    n = points.df.count()
    shards = max(1, -(-n // shard_rows))
    if shards == 1:
        return Choice("kernel", 1, f"{n} points fit one task")
    if whole and n <= WORKER_ROWS:
        return Choice("batches", 1, f"{n} points in one graph, which every worker can hold")
    if whole:
        return Choice("rounds", 1, f"{n} points in one graph, more than a worker holds")
    return Choice("sharded", shards, f"{n} points in shards of {shard_rows}")


def normalise_metric(points: PointSet, tolerance: float = 1e-6) -> PointSet:
    """cosine becomes l2 if all norms are 1: the order of neighbours is the same, and cheaper."""
    from proxigraph.functions.distance import norm

    if points.metric != "cosine":
        return points
    off = points.plain().filter(F.abs(norm("vec") - 1.0) > tolerance).limit(1).count()
    return points if off else PointSet(points.df, points.id, points.vec, "l2")


def build(points: PointSet, method: str = "alpha", shard_rows: int = SHARD_ROWS, shard_kind: str = "cells", whole: bool = False, **params) -> GraphIndex:
    """Build by the method with the engine that choose_engine names; only the alpha graph has engines for
    one graph that no single task builds."""
    points = normalise_metric(points)
    engine = choose_engine(points, shard_rows, whole).engine
    if engine in ("batches", "rounds"):
        if method != "alpha":
            raise ValueError("one graph over more points than a shard holds is built for the alpha method only")
        return BUILDERS[method](points, engine=engine, **params)
    return BUILDERS[method](points, shard_rows=shard_rows, shard_kind=shard_kind, **params)
