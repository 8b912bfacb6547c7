"""Ranking a schema's columns for a question and keeping the best, with their keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from densesql.functions.text import tokens

K1, B = 1.2, 0.75


def documents(columns: DataFrame) -> DataFrame:
    """``columns`` with ``words``: the parts of table and column names, plurals folded."""
    stem = lambda w: F.regexp_replace(w, "(ies|es|s)$", "")
    parts = F.split(F.lower(F.concat_ws("_", "table_name", "column_name")), "_")
    return columns.withColumn("words", F.transform(F.filter(parts, lambda w: F.length(w) > 1), stem))


def rank(questions: DataFrame, columns: DataFrame, k: int = 30, scorer: str = "tfidf", references: DataFrame | None = None) -> DataFrame:
    """(question_id, db_id, table_name, column_name, score, place) of the ``k`` best columns a question.

    ``columns`` is matched as one schema per db_id.  With ``references`` the key columns
    between kept tables are added beyond ``k``.
    """
    docs = documents(columns).select("db_id", "table_name", "column_name", "words")
    n_docs = docs.groupBy("db_id").agg(F.count(F.lit(1)).alias("n_cols"), F.avg(F.size("words")).alias("mean_size"))
    terms = docs.select("db_id", "table_name", "column_name", F.size("words").alias("size"), F.explode("words").alias("word"))
    tf = terms.groupBy("db_id", "table_name", "column_name", "size", "word").agg(F.count(F.lit(1)).alias("tf"))
    df = tf.groupBy("db_id", "word").agg(F.count(F.lit(1)).alias("df"))
    weighed = tf.join(df, ["db_id", "word"]).join(n_docs, "db_id")
    if scorer == "tfidf":
        weight = F.col("tf") * F.log(1 + F.col("n_cols") / F.col("df"))
    else:
        idf = F.log(1 + (F.col("n_cols") - F.col("df") + 0.5) / (F.col("df") + 0.5))
        weight = idf * F.col("tf") * (K1 + 1) / (F.col("tf") + K1 * (1 - B + B * F.col("size") / F.col("mean_size")))
    weighed = weighed.select("db_id", "table_name", "column_name", "word", weight.alias("w"))
    stem = F.transform(tokens(F.col("question")), lambda w: F.regexp_replace(w, "(ies|es|s)$", ""))
    asked = questions.select("question_id", "db_id", F.explode(F.array_distinct(stem)).alias("word"))
    hits = asked.join(weighed, ["db_id", "word"]).groupBy("question_id", "db_id", "table_name", "column_name").agg(F.sum("w").alias("score"))
    every = questions.select("question_id", "db_id").join(docs.select("db_id", "table_name", "column_name"), "db_id")
    scored = every.join(hits, ["question_id", "db_id", "table_name", "column_name"], "left").withColumn("score", F.coalesce("score", F.lit(0.0)))
    order = Window.partitionBy("question_id").orderBy(F.round("score", 9).desc(), "table_name", "column_name")
    best = scored.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)
    if references is None:
        return best
    kept = best.select("question_id", "db_id", "table_name").distinct()
    fits = references.join(kept, ["db_id", "table_name"]).join(kept.select("question_id", F.col("table_name").alias("ref_table")), ["question_id", "ref_table"])
    ends = fits.select("question_id", "db_id", F.explode(F.array(F.struct("table_name", "column_name"), F.struct(F.col("ref_table").alias("table_name"), F.col("ref_column").alias("column_name")))).alias("e"))
    keys = ends.select("question_id", "db_id", "e.*").distinct().join(best, ["question_id", "table_name", "column_name"], "left_anti")
    return best.unionByName(keys.select("question_id", "db_id", "table_name", "column_name", F.lit(0.0).alias("score"), F.lit(None).cast("int").alias("place")))


def recall(ranked: DataFrame, gold: DataFrame, ks: tuple[int, ...] = (5, 10, 20, 30)) -> DataFrame:
    """(k, recall): share of each question's gold columns (question_id, column_name) among its first k, averaged."""
    hit = gold.join(ranked.select("question_id", "column_name", "place"), ["question_id", "column_name"], "left")
    each = hit.withColumn("k", F.explode(F.array(*map(F.lit, ks))))
    per = each.groupBy("k", "question_id").agg(F.avg(F.coalesce(F.col("place") <= F.col("k"), F.lit(False)).cast("double")).alias("r"))
    return per.groupBy("k").agg(F.avg("r").alias("recall"))
