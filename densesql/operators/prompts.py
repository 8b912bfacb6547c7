"""Prompt rows: one rendered schema for each question, and the system messages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densesql.functions.completion import CLOSE, OPEN

_TASK = "Answer the question about the database with exactly one SQL statement."


def system_message(style: str = "tagged") -> str:
    """``tagged`` asks for a reasoning block first; ``native`` leaves out the layout, for models that reason on their own."""
    if style == "native":
        return f"{_TASK} Write nothing but the statement."
    return f"{_TASK} First reason inside {OPEN} and {CLOSE}, then write the statement and nothing else."


def render_user_prompt(questions: DataFrame, columns: DataFrame, references: DataFrame, evidence: bool = True) -> DataFrame:
    """(question_id, user_prompt): schema, keys, question and optional evidence in one text.

    ``columns`` may hold a question_id (a filtered schema per question) or only a db_id.
    """
    by = ["question_id"] if "question_id" in columns.columns else ["db_id"]
    cols = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", "column_name", "data_type"))), lambda c: F.concat(c["column_name"], F.lit(" "), c["data_type"])), ", ")
    tables = columns.groupBy(*by, "table_name").agg(F.format_string("%s(%s)", F.col("table_name"), cols).alias("line"))
    schema = tables.groupBy(*by).agg(F.array_join(F.array_sort(F.collect_list("line")), "\n").alias("schema"))
    key = F.format_string("%s.%s = %s.%s", "table_name", "column_name", "ref_table", "ref_column")
    keys = references.groupBy("db_id").agg(F.array_join(F.array_sort(F.collect_list(key)), "; ").alias("keys"))
    joined = questions.join(schema, by, "left").join(keys, "db_id", "left")
    parts = [F.lit("Schema:\n"), F.coalesce("schema", F.lit("")), F.lit("\nKeys: "), F.coalesce("keys", F.lit("none")), F.lit("\nQuestion: "), F.col("question")]
    if evidence:
        parts += [F.when(F.coalesce("evidence", F.lit("")) != "", F.concat(F.lit("\nEvidence: "), F.col("evidence"))).otherwise("")]
    return joined.select("question_id", F.concat(*parts).alias("user_prompt"))
