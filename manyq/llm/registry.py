"""The queries of this subpackage and the SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from manyq.llm import byte_bpe, exact_dedup, html_text, line_dedup, near_dedup, nearest, packing, secret_scan, substring_dedup, toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_line_dedup": line_dedup.op1_line_dedup,
        "op2_exact_dedup": exact_dedup.op2_exact_dedup,
        "op3_html_text": html_text.op3_html_text,
        "op4_secret_scan": secret_scan.op4_secret_scan,
        "op5_near_dedup": near_dedup.op5_near_dedup,
        "op6_packing": packing.op6_packing,
        "op7_nearest": nearest.op7_nearest,
        "op8_byte_bpe": byte_bpe.op8_byte_bpe,
        "op9_toxicity": toxicity.op9_toxicity,
        "op10_substring_dedup": substring_dedup.op10_substring_dedup,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_line_dedup": line_dedup.ORACLE_SQL,
        "op2_exact_dedup": exact_dedup.ORACLE_SQL,
        "op4_secret_scan": secret_scan.ORACLE_SQL,
        "op5_near_dedup": near_dedup.ORACLE_SQL,
    }
