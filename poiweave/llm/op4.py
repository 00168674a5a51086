"""Query op4_identify_language."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .language import identify_language
from .session import table


def op4_identify_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document."""
    return identify_language(table(spark, sf_dir, "documents"))
