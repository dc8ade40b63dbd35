"""Operators for training-data pipelines; nothing else in the library imports this subpackage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, decontaminate, line_dedup, ngram_join, quality, secrets, topk, toxicity, warc, wordpiece


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """Each operator over its whole table, with production parameters."""
    return {
        "op1_quality_classifier": quality.query,
        "op2_line_dedup": line_dedup.query,
        "op3_benchmark_decontamination": decontaminate.query,
        "op4_warc_derivatives": warc.query,
        "op5_ngram_jaccard_join": ngram_join.query,
        "op6_secret_scans": secrets.query,
        "op7_token_counts": wordpiece.query,
        "op8_byte_bpe": bpe.query,
        "op9_exact_top_k": topk.query,
        "op10_toxicity": toxicity.query,
    }


def oracle_sql() -> dict[str, str]:
    """SQL for the operators that SQL can express."""
    return {
        "op3_benchmark_decontamination": decontaminate.SQL,
        "op5_ngram_jaccard_join": ngram_join.SQL,
        "op9_exact_top_k": topk.SQL,
    }
