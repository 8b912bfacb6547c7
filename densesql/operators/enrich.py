"""Reference pools: verified samples next to the gold, and the audit of what slipped in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densesql.functions.similarity import jaccard
from densesql.operators.atoms import Options, decompose


def build_pool(questions: DataFrame, judged: DataFrame | None, options: Options = Options()) -> DataFrame:  # noqa: B008
    """(question_id, ref_id, sql, op_keys, is_gold, empty_result); gold is ref 0, distinct structures follow.

    ``judged`` holds the samples with sql and correct; None gives the gold-only pool.
    """
    gold = questions.select("question_id", F.col("gold_sql").alias("sql"), F.lit(True).alias("is_gold"))
    texts = gold
    if judged is not None:
        texts = gold.unionByName(judged.where("correct").select("question_id", "sql", F.lit(False).alias("is_gold")))
    keyed = decompose(texts, "sql", options).select("question_id", "sql", "is_gold", "op_keys")
    distinct = keyed.groupBy("question_id", "op_keys").agg(F.max("is_gold").alias("is_gold"), F.min_by("sql", F.struct(~F.col("is_gold"), "sql")).alias("sql"))
    from pyspark.sql import Window

    order = Window.partitionBy("question_id").orderBy(F.desc("is_gold"), "sql")
    pool = distinct.withColumn("ref_id", F.row_number().over(order) - 1)
    if judged is None:
        return pool.withColumn("empty_result", F.lit(None).cast("boolean"))
    empty = judged.groupBy("question_id").agg((F.max("gold_rows") == 0).alias("empty_result"))
    return pool.join(empty, "question_id", "left")


def empty_rate(judged: DataFrame) -> DataFrame:
    """One row (n, n_empty, share) over questions."""
    per = judged.groupBy("question_id").agg((F.max("gold_rows") == 0).alias("empty"))
    return per.agg(F.count(F.lit(1)).alias("n"), F.count_if("empty").alias("n_empty"), F.avg(F.col("empty").cast("double")).alias("share"))


def _with_gold(pool: DataFrame) -> DataFrame:
    gold = pool.where("is_gold").select("question_id", F.col("op_keys").alias("gold_keys"), F.col("sql").alias("gold_sql"))
    return pool.where("not is_gold").join(gold, "question_id").withColumn("overlap", jaccard(F.col("op_keys"), F.col("gold_keys")))


def empty_guard(pool: DataFrame, min_overlap: float = 0.5) -> DataFrame:
    """The pool without what an empty gold lets in: always-false filters and structures far from the gold."""
    vacuous = F.exists("op_keys", lambda k: F.rlike(k, F.lit(r"^where\.condition\(=, [01], [01]\)$")) & (k != "where.condition(=, 1, 1)") & (k != "where.condition(=, 0, 0)"))
    suspect = _with_gold(pool).where(F.coalesce("empty_result", F.lit(False)) & (vacuous | (F.col("overlap") < min_overlap)))
    return pool.join(suspect.select("question_id", "ref_id"), ["question_id", "ref_id"], "left_anti")


def audit(pool: DataFrame, n: int = 100) -> DataFrame:
    """Up to ``n`` kept variants with non-empty results in hash order, their overlap, and whether only DISTINCT differs."""
    found = _with_gold(pool).where(~F.coalesce("empty_result", F.lit(False)))
    change = F.array_union(F.array_except("op_keys", "gold_keys"), F.array_except("gold_keys", "op_keys"))
    only_distinct = (F.size(change) > 0) & F.forall(change, lambda k: k == "select.distinct()")
    shown = found.select("question_id", "ref_id", "sql", "overlap", only_distinct.alias("only_distinct"))
    return shown.orderBy(F.xxhash64("question_id", "sql"), "question_id", "ref_id").limit(n)


def overlap_summary(pool: DataFrame) -> DataFrame:
    """One row with the distribution of overlap between kept variants and gold."""
    q = lambda p: F.percentile("overlap", F.lit(p))
    return _with_gold(pool).agg(F.count(F.lit(1)).alias("n"), q(0.1).alias("p10"), q(0.5).alias("p50"), q(0.9).alias("p90"), F.avg("overlap").alias("mean"))
