"""Query op8_mix_sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .mixing import mix_digest
from .session import table


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many words of each document the mix of all sources takes."""
    return mix_digest(table(spark, sf_dir, "documents"))
