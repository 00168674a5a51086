"""Functions and table functions for SQL text, and vectorised UDF counterparts of native expressions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .graph import knn_graph, normalise_adjacency, unit_weights
from .kmeans import bisect
from .places import budget_of


@F.pandas_udf(T.DoubleType())
def vec_norm(v: pd.Series) -> pd.Series:
    return pd.Series([float(np.sqrt(np.square(np.asarray(x, float)).sum())) if x is not None else None for x in v])


@F.pandas_udf(T.DoubleType())
def weighted_mean(x: pd.Series, w: pd.Series) -> float:
    total = w.sum()
    return float((x * w).sum() / total) if total else float("nan")


@F.udtf(returnType=T.StructType([T.StructField("tx", T.LongType()), T.StructField("ty", T.LongType())]))
class TileRing:
    """The tiles within ``k`` steps of a tile."""

    def eval(self, x: int, y: int, k: int) -> Iterator[tuple[int, int]]:
        for i in range(-k, k + 1):
            for j in range(-k, k + 1):
                yield x + i, y + j


@F.udtf(returnType=T.StructType([T.StructField(n, T.LongType()) for n in ("region", "n_places", "n")]))
class PlaceSplit:
    """Places of each partition of a table argument (region, poi_id, h, r)."""

    def __init__(self) -> None:
        self.rows: list[Row] = []

    def eval(self, row: Row) -> None:
        self.rows.append(row)

    def terminate(self) -> Iterator[tuple[int, int, int]]:
        if self.rows:
            x = np.array([r["h"] for r in self.rows], float)
            tree = bisect(np.array([r["poi_id"] for r in self.rows]), x, budget_of(len(x), self.rows[0]["r"]))
            yield self.rows[0]["region"], len(set(tree.leaf.tolist())), len(x)


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL text."""
    spark.udf.register("vec_norm", vec_norm)
    spark.udtf.register("tile_ring", TileRing)
    spark.udtf.register("place_split", PlaceSplit)


def split_places_sql(spark: SparkSession, h: DataFrame, r: str) -> DataFrame:
    """``place_split`` over a view, one partition for each region."""
    register(spark)
    h.select(F.col("zip_id").cast("long").alias("region"), "poi_id", "h", F.lit(r).alias("r")).createOrReplaceTempView("poiweave_features")
    return spark.sql("SELECT s.region, s.n_places, s.n FROM place_split(TABLE(poiweave_features) PARTITION BY region) AS s")


def register_graph(spark: SparkSession, poi: DataFrame, h: DataFrame, edges: DataFrame | None = None) -> None:
    """Views for SQL text: ``poiweave_poi``, ``poiweave_edge``, ``poiweave_a_hat`` (dst, src, w) and ``poiweave_h`` (poi_id, h). Unweighted neighbours if no edges are given."""
    edges = unit_weights(knn_graph(poi)) if edges is None else edges
    for name, df in (("poi", poi), ("edge", edges), ("a_hat", normalise_adjacency(edges, poi)), ("h", h)):
        df.createOrReplaceTempView(f"poiweave_{name}")
    register(spark)


def hop_sql(source: str, d: int) -> str:
    """One multiplication by the graph as SQL text."""
    return f"SELECT a.dst AS poi_id, array({', '.join(f'sum(a.w * x.h[{i}])' for i in range(d))}) AS h FROM poiweave_a_hat a JOIN {source} x ON x.poi_id = a.src GROUP BY a.dst"


def region_embedding_sql(spark: SparkSession, d: int, alpha: tuple[float, ...]) -> DataFrame:
    """zip_id, n_poi, z: hops, their combination and the mean of each region in one SQL statement."""
    levels = ["hop0 AS (SELECT poi_id, h FROM poiweave_h)"] + [f"hop{k} AS ({hop_sql(f'hop{k - 1}', d)})" for k in range(1, len(alpha))]
    mixed = ", ".join(" + ".join(f"{a}D * hop{k}.h[{i}]" for k, a in enumerate(alpha)) + f" AS c{i}" for i in range(d))
    joins = " ".join(f"JOIN hop{k} ON hop{k}.poi_id = hop0.poi_id" for k in range(1, len(alpha)))
    means = ", ".join(f"round(avg(c{i}), 6) + 0.0" for i in range(d))
    return spark.sql(f"WITH {', '.join(levels)}, mixed AS (SELECT hop0.poi_id, {mixed} FROM hop0 {joins}) SELECT p.zip_id, count(*) AS n_poi, array({means}) AS z FROM mixed JOIN poiweave_poi p ON p.poi_id = mixed.poi_id GROUP BY p.zip_id")
