"""Query op3_find_pii."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .pii import find_pii
from .session import table


def op3_find_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data of all documents, plain and disguised."""
    return find_pii(table(spark, sf_dir, "documents"))
