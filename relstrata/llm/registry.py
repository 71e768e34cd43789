"""Queries and oracle SQL of the text operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import decontaminate, html_main, line_dedup, mixing, quality, secret_scan, simhash, suffix_dedup, token_output, url_filter


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = [
        simhash.op1_simhash_near_dedup,
        token_output.op2_token_output,
        quality.op3_quality_rules,
        secret_scan.op4_secret_scan,
        mixing.op5_mixing,
        decontaminate.op6_decontamination,
        line_dedup.op7_line_dedup,
        url_filter.op8_url_filter,
        html_main.op9_html_extraction,
        suffix_dedup.op10_suffix_array_dedup,
    ]
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {
        "op5_mixing": mixing.ORACLE,
        "op6_decontamination": decontaminate.ORACLE,
        "op7_line_dedup": line_dedup.ORACLE,
        "op8_url_filter": url_filter.ORACLE,
    }
