"""Query op7_histogram_shards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .session import table
from .sharding import shard_digest


def op7_histogram_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 16 shards of near equal bytes."""
    return shard_digest(table(spark, sf_dir, "documents"))
