"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession

from . import op1, op2, op3, op4, op5, op6, op7, op8, op9, op10


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_decontaminate": op1.op1_decontaminate,
        "op2_ngram_jaccard": op2.op2_ngram_jaccard,
        "op3_find_pii": op3.op3_find_pii,
        "op4_identify_language": op4.op4_identify_language,
        "op5_nearest": op5.op5_nearest,
        "op6_score_quality": op6.op6_score_quality,
        "op7_histogram_shards": op7.op7_histogram_shards,
        "op8_mix_sources": op8.op8_mix_sources,
        "op9_format_chat": op9.op9_format_chat,
        "op10_score_toxicity": op10.op10_score_toxicity,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    pipeline = {"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {}
    return pipeline | {
        "op1_decontaminate": op1.SQL,
        "op2_ngram_jaccard": op2.SQL,
        "op9_format_chat": op9.SQL,
    }
