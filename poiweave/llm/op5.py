"""Query op5_nearest."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .neighbours import nearest
from .session import table


def op5_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five nearest vectors of each query row."""
    return nearest(table(spark, sf_dir, "embeddings"))
