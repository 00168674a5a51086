"""All queries of the engine by name, with their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .plans.plan import PlaceEngine
from .queries import evaluation, features, graph, places, prep, streams, surround

MODULES = (prep, graph, features, places, evaluation, surround, streams)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places of all regions: neighbours' graph, one hop of propagation, bisecting clustering, summaries."""
    return PlaceEngine(spark).load(sf_dir).alpha(0.5, 0.5).frames("places")["places"].select("zip_id", "place_id", "n_poi", "lat", "lon", "sse", "z")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: text for m in MODULES for name, text in m.SQL.items()}
