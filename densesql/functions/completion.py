"""The fixed completion layout: one reasoning block, then one SQL statement.

Everything is a column expression, so splitting and checking stay in generated code.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE = "<think>", "</think>"
QUOTED = r"'(?:[^']|'')*'|\"[^\"]*\""


def _count(text: Column, piece: str) -> Column:
    return ((F.length(text) - F.length(F.replace(text, F.lit(piece), F.lit("")))) / len(piece)).cast("int")


def trace_of(completion: Column) -> Column:
    """Text of the first reasoning block, trimmed; empty without one."""
    return F.trim(F.regexp_extract(F.coalesce(completion, F.lit("")), rf"(?s){OPEN}(.*?){CLOSE}", 1))


def sql_of(completion: Column) -> Column:
    """What follows the last closing tag, without blanks and one closing semicolon."""
    rest = F.substring_index(F.coalesce(completion, F.lit("")), CLOSE, -1)
    return F.regexp_replace(F.regexp_replace(rest, r"^\s+|\s+$", ""), r"\s*;\s*$", "")


def format_error(completion: Column, strict: bool = True) -> Column:
    """The first broken layout rule, or null."""
    text = F.coalesce(completion, F.lit(""))
    opens, closes = _count(text, OPEN), _count(text, CLOSE)
    lead = F.substring_index(text, OPEN, 1)
    sql = sql_of(text)
    bare = F.regexp_replace(sql, QUOTED, "")
    return (
        F.when((opens == 0) & (closes == 0), "no_block")
        .when((opens != closes) & (opens + closes > 0) & ((opens == 0) | (closes == 0)), "unclosed")
        .when((opens > 1) | (closes > 1), "many_blocks")
        .when(F.instr(text, CLOSE) < F.instr(text, OPEN), "unclosed")
        .when(lead != "" if strict else F.trim(lead) != "", "prefix_text")
        .when(F.regexp_replace(trace_of(text), r"\s+", "") == "", "empty_trace")
        .when(sql == "", "empty_sql")
        .when(F.instr(bare, ";") > 0, "many_statements")
        .when(~F.rlike(sql, F.lit(r"(?i)^(select\b|with\b|\()")), "not_a_query")
    )


def split(rollouts: DataFrame, completion: str = "completion", strict: bool = True) -> DataFrame:
    """Add trace, sql, format_error and format_ok."""
    text = F.col(completion)
    return rollouts.withColumns(
        {"trace": trace_of(text), "sql": sql_of(text), "format_error": format_error(text, strict)}
    ).withColumn("format_ok", F.col("format_error").isNull())
