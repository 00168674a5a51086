"""Query op6_score_quality."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .quality import score_quality
from .session import table


def op6_score_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality scores of all documents."""
    return score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
