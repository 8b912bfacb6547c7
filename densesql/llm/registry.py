"""The subpackage's queries and their SQL, for the entry module to add."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from densesql.llm import op1_secrets, op2_simhash, op3_tokens, op4_mix, op5_shards, op6_lines, op7_rollups, op8_links, op9_quality, op10_benchmark


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_secret_scan": op1_secrets.op1_secret_scan,
        "op2_simhash": op2_simhash.op2_simhash,
        "op3_token_files": op3_tokens.op3_token_files,
        "op4_mix": op4_mix.op4_mix,
        "op5_shards": op5_shards.op5_shards,
        "op6_line_dedup": op6_lines.op6_line_dedup,
        "op7_token_rollups": op7_rollups.op7_token_rollups,
        "op8_url_filter": op8_links.op8_url_filter,
        "op9_quality": op9_quality.op9_quality,
        "op10_benchmark": op10_benchmark.op10_benchmark,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_mix": op4_mix.ORACLE, "op7_token_rollups": op7_rollups.ORACLE, "op10_benchmark": op10_benchmark.ORACLE}
