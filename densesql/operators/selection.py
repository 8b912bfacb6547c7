"""Choosing one candidate a question: votes over results, single picks and bounds.

Candidates have question_id, rollout_id, status, result (null if it failed) and correct.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F



def by_question() -> WindowSpec:
    return Window.partitionBy("question_id")


def groups(cands: DataFrame, weight: Column | None = None, empty_votes: bool = True) -> DataFrame:
    """(question_id, result, size, weight, first_id, correct): the execution groups; failed candidates form none."""
    voters = cands.where(F.col("result").isNotNull())
    if not empty_votes:
        voters = voters.where("n_rows > 0")
    heavy = F.sum(weight if weight is not None else F.lit(1.0))
    return voters.groupBy("question_id", "result").agg(
        F.count(F.lit(1)).alias("size"), heavy.alias("weight"), F.min("rollout_id").alias("first_id"), F.max("correct").alias("correct")
    )


def majority(cands: DataFrame, weight: Column | None = None, empty_votes: bool = True, ties: str = "first") -> DataFrame:
    """(question_id, rollout_id, size, share, correct): the heaviest group's first member.

    Ties go to the larger group and then the smallest rollout (``ties='first'``) or the
    largest (``'last'``).  Where nothing ran the first parseable candidate stands, else
    the first, and counts as wrong.
    """
    found = groups(cands, weight, empty_votes)
    tie = F.col("first_id").asc() if ties == "first" else F.col("first_id").desc()
    order = by_question().orderBy(F.round("weight", 9).desc(), F.desc("size"), tie)
    best = found.withColumn("_r", F.row_number().over(order)).where("_r = 1")
    parseable = F.min(F.when(F.col("status") != "parse", F.col("rollout_id")))
    every = cands.groupBy("question_id").agg(F.count(F.lit(1)).alias("k"), F.coalesce(parseable, F.min("rollout_id")).alias("spare"))
    joined = every.join(best, "question_id", "left")
    return joined.select(
        "question_id", F.coalesce("first_id", "spare").alias("rollout_id"), F.coalesce("size", F.lit(0)).cast("long").alias("size"),
        (F.coalesce("size", F.lit(0)) / F.col("k")).alias("share"), F.coalesce("correct", F.lit(False)).alias("correct"),
    )


def single(cands: DataFrame, how: str = "first") -> DataFrame:
    """(question_id, rollout_id, correct): ``first``, ``best_logp``, ``first_valid`` or a repeatable ``random`` one."""
    key = {
        "first": F.struct("rollout_id"),
        "best_logp": F.struct((-F.col("logp")).alias("a"), "rollout_id") if "logp" in cands.columns else F.struct("rollout_id"),
        "first_valid": F.struct((F.col("status") == "parse").alias("a"), "rollout_id"),
        "random": F.struct(F.xxhash64("question_id", "rollout_id").alias("a"), "rollout_id"),
    }[how]
    best = F.min_by(F.struct("rollout_id", "correct"), key).alias("b")
    return cands.groupBy("question_id").agg(best).select("question_id", "b.rollout_id", "b.correct")


def oracle(cands: DataFrame) -> DataFrame:
    """(question_id, correct): whether any candidate is correct, the upper bound of every selection."""
    return cands.groupBy("question_id").agg(F.max("correct").alias("correct"))


def majority_incremental(cands: DataFrame) -> DataFrame:
    """(question_id, decided_at): the number of candidates after which the remaining ones cannot change the winner."""
    order = by_question().orderBy("rollout_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = cands.withColumns({"at": F.row_number().over(by_question().orderBy("rollout_id")), "k": F.count(F.lit(1)).over(by_question())})
    per = Window.partitionBy("question_id", "result").orderBy("rollout_id").rowsBetween(Window.unboundedPreceding, 0)
    run = seen.withColumn("mine", F.when(F.col("result").isNotNull(), F.count(F.lit(1)).over(per)).otherwise(0))
    lead = run.withColumn("top", F.max("mine").over(order))
    tops = lead.withColumn("top_of", F.max_by("result", F.struct("mine", -F.col("rollout_id"))).over(order))
    rest = F.max(F.when(~F.col("result").eqNullSafe(F.col("top_of")), F.col("mine"))).over(order)
    decided = tops.withColumn("second", F.coalesce(rest, F.lit(0))).where(F.col("top") - F.col("second") > F.col("k") - F.col("at"))
    return cands.select("question_id").distinct().join(decided.groupBy("question_id").agg(F.min("at").alias("decided_at")), "question_id", "left").join(
        seen.groupBy("question_id").agg(F.max("k").alias("k")), "question_id"
    ).select("question_id", F.coalesce("decided_at", "k").cast("long").alias("decided_at"))
