"""Connected components of an edge table by alternating large-star and small-star rounds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import cut, small

#: Up to so many rows a round's table of least neighbours is broadcast, so a hub's edges are not gathered in one task.
BROADCAST_NODES = 200_000


def connected_components(edges: DataFrame, most_rounds: int = 40) -> DataFrame:
    """``node``, ``root`` (the smallest node of the component) for every node of ``edges`` (a, b: of any type with an order).

    Every round hangs nodes below smaller ones and writes the new edges, which never grow in number. Beyond
    ``BROADCAST_NODES`` edges the joins shuffle, and adaptive execution splits a hub's partition.
    """
    ordered = cut(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    now, before = _state(ordered), None
    for _ in range(most_rounds):
        n = 2 * now[0]
        both = ordered.unionByName(ordered.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")).withColumnRenamed("u", "c")
        large = ordered.join(small(least, n, BROADCAST_NODES), F.col("v") == F.col("c")).select("u", F.col("m").alias("v"))  # larger neighbours hang below the least one
        every = large.unionByName(ordered)
        down = every.groupBy("u").agg(F.min("v").alias("m"))
        hung = every.join(small(down.withColumnRenamed("u", "c"), n, BROADCAST_NODES), F.col("u") == F.col("c")).select(F.greatest("v", "m").alias("u"), F.col("m").alias("v"))
        ordered = cut(hung.unionByName(down.select("u", F.col("m").alias("v"))).filter("u <> v").distinct())
        before, now = now, _state(ordered)
        if now == before:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = ordered.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
    return roots.unionByName(roots.select("root").distinct().select(F.col("root").alias("node"), "root"))


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("v").cast("decimal(38,0)")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def least_labels(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """The smallest node of each of ``n`` nodes' components under the edges (a, b), in one task: roots of edges' ends hang below the smaller one, paths are halved until they end."""
    root = np.arange(n)
    while len(a):
        p, q = root[a], root[b]
        apart = p != q
        a, b, p, q = a[apart], b[apart], p[apart], q[apart]
        np.minimum.at(root, np.maximum(p, q), np.minimum(p, q))
        up = root[root]
        while (up != root).any():
            root, up = up, up[up]
    return root
