"""The registered queries of the training-data operators, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, jaccard_join, language_id, line_dedup, media, packing, quality_fm, quality_rules, substring_dedup, suffix_dedup


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_bpe_roundtrip": lambda s, d: bpe.bpe_digest(_documents(s, d)),
        "op2_ngram_jaccard": lambda s, d: jaccard_join.ngram_components(_documents(s, d)),
        "op3_substring_dedup": lambda s, d: substring_dedup.digest(_documents(s, d)),
        "op4_quality_rules": lambda s, d: quality_rules.digest(_documents(s, d)),
        "op5_suffix_dedup": lambda s, d: suffix_dedup.digest(_documents(s, d)),
        "op6_media_columns": lambda s, d: media.media_digest(_documents(s, d)),
        "op7_quality_classifier": lambda s, d: quality_fm.digest(_documents(s, d), s.read.parquet(f"{d}/labels.parquet")),
        "op8_line_dedup": lambda s, d: line_dedup.digest(_documents(s, d)),
        "op9_packing": lambda s, d: packing.pack(_documents(s, d)),
        "op10_language_id": lambda s, d: language_id.digest(_documents(s, d)),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_ngram_jaccard": jaccard_join.SQL,
        "op3_substring_dedup": substring_dedup.SQL,
        "op4_quality_rules": quality_rules.SQL,
    }
