"""Queries of the training-data operators and, where SQL can say it, their DuckDB equivalents."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bin_packing, fingerprints, near_dedup, quality_rules, secret_scan, sentencepiece_codec, substring_dedup, token_output, url_templates, warc_archive


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_token_shards": token_output.query,
        "op2_substring_dedup": substring_dedup.query,
        "op3_secret_scan": secret_scan.query,
        "op4_warc_archive": warc_archive.query,
        "op5_quality_rules": quality_rules.query,
        "op6_sentencepiece": sentencepiece_codec.query,
        "op7_url_templates": url_templates.query,
        "op8_best_fit_packing": bin_packing.query,
        "op9_near_dedup": near_dedup.query,
        "op10_fingerprints": fingerprints.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_substring_dedup": substring_dedup.ORACLE,
        "op4_warc_archive": warc_archive.ORACLE,
        "op5_quality_rules": quality_rules.ORACLE,
        "op7_url_templates": url_templates.ORACLE,
        "op9_near_dedup": near_dedup.ORACLE,
    }
