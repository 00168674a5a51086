"""Query op10_score_toxicity."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .session import table
from .toxicity import score_toxicity


def op10_score_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity scores of all documents."""
    return score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
