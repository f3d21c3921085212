"""Connected components of a link table, by alternating star contractions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.runtime import discard, settle


def local_components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest reachable index of each of n nodes under links a[i]-b[i]."""
    label = np.arange(n)
    while True:
        la, lb = label[a], label[b]
        open_ = la != lb
        if not open_.any():
            return label
        np.minimum.at(label, np.maximum(la, lb)[open_], np.minimum(la, lb)[open_])
        while not np.array_equal(label, label[label]):
            label = label[label]


def _digest(stars: DataFrame) -> tuple:
    row = stars.agg(F.count("*").alias("n"), F.expr("bit_xor(xxhash64(u, v))").alias("x")).first()
    return row["n"], row["x"]


def components(links: DataFrame) -> DataFrame:
    """links(u long, v long) -> (u, v): every linked node but the smallest of its component, with
    that smallest node as v.

    Each round first hangs every node's larger neighbours on its smallest neighbour, then every
    node's smaller neighbours on the smallest of them; the rounds grow with the logarithm of the
    longest path. Joins may meet a hub: adaptive execution splits them. Self links and null ends
    are ignored; an empty table gives an empty result.
    """
    spark = links.sparkSession
    spent: list[str] = []
    last: list[str] = []
    edges = settle(
        links.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(),
        "links", last,
    )
    before = _digest(edges)
    while before[0]:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = (
            both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .filter("u <> v").distinct()
        )
        large = settle(large, "large-star", spent)
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        )
        spent += last
        last.clear()
        edges = settle(small, "small-star", last)
        discard(spark, spent)
        after = _digest(edges)
        if after == before:
            break
        before = after
    return edges
