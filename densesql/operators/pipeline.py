"""From questions to scored rollouts, and from candidates to one answer a question."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import completion
from densesql.operators import atoms, corpus, embed, enrich, execute, grpo, memory, policy, rewards, schema_filter, selection
from densesql.plans.staging import Staging
from densesql.sources.tables import schema_columns, schema_references


def scored_rollouts(
    spark: SparkSession, sf_dir: str, tier: str = "s", group: int = 32, temperature: float = 1.0, k: int = 20, scope: str = "cross",
    shaping: str = "S3", weights: tuple[float, float, float, float] = (1, 1, 1, 1), gate: str = "hard", staging: Staging | None = None,
) -> DataFrame:
    """The dense reward of every rollout, staged: split, run, overlap, memory, total, advantage.

    Text travels as far as parsing and encoding and no further; correct rollouts skip the
    neighbour look-up, whose value they would not use.
    """
    staging = staging or Staging(spark, "scored")
    questions = corpus.questions(spark)
    parsed = completion.split(corpus.rollouts(spark, group, tier, temperature))
    drawn = completion.split(reference_draws(spark, tier))
    bank = completion.split(corpus.bank(spark).where(F.col("teacher") == corpus.STRONGEST))
    texts = questions.select("db_id", F.col("gold_sql").alias("sql"))
    for part in (parsed, drawn, bank):
        texts = texts.union(part.select("db_id", "sql"))
    executed = execute.run_new(spark, sf_dir, texts)  # every distinct statement once a session: tiers share many
    judged = staging.table(execute.judge(spark, sf_dir, parsed, questions, executed), f"judged-{tier}-{temperature}")
    pool = staging.table(enrich.build_pool(questions, execute.judge(spark, sf_dir, drawn, questions, executed)), f"pool-{tier}-{temperature}")
    decomposed = staging.table(atoms.decompose(judged, "sql"), f"ops-{tier}-{temperature}")
    best = atoms.best_reference(decomposed, pool)
    verified = execute.judge(spark, sf_dir, bank, questions, executed).where("correct and format_ok")
    store = embed.encode(verified.withColumn("entry_id", F.col("question_id")), "entry_id", "trace", keep=("entry_id", "db_id"))  # one teacher, one answer a question
    keyed = decomposed.withColumn("query_id", -1 - (F.col("question_id") * 1000 + F.col("rollout_id")))
    asked = embed.encode(keyed.where("format_ok and not correct"), "query_id", "trace", keep=("query_id", "db_id"))
    asked, store = staging.table(asked, f"asked-{tier}-{temperature}"), staging.table(store, f"store-{tier}-{temperature}")
    found = memory.scores(asked, memory.lookup(asked, store, k, scope), store)
    joined = keyed.join(best, ["question_id", "rollout_id"], "left").join(found.withColumnRenamed("score", "mem_score"), "query_id", "left")
    col = F.col
    overlap = F.coalesce("overlap", F.lit(0.0))
    full = joined.withColumns(
        {
            "overlap": overlap,
            "mem_score": F.coalesce("mem_score", F.lit(0.0)),
            "format": rewards.format_reward(col("format_ok")),
            "exec": rewards.exec_reward(col("status"), col("correct")),
            "binary": rewards.exec_reward(col("status"), col("correct"), "binary"),
            "atomic": rewards.atomic_reward(overlap, col("correct"), shaping),
            "mem": memory.memory_reward(F.coalesce("mem_score", F.lit(0.0)), col("format_ok"), col("correct")),
        }
    )
    total = rewards.compose(full, weights, gate)
    return staging.table(grpo.advantages(total), f"scored-{tier}-{temperature}-{gate}")


def reference_draws(spark: SparkSession, tier: str, n: int = 30) -> DataFrame:
    """A separate draw of ``n`` candidates a question at temperature 1, from which references are taken."""
    return corpus.rollouts(spark, n, tier, 1.0, seed=corpus.REFERENCE_SEED)


def candidate_table(scored: DataFrame) -> DataFrame:
    """Scored rollouts as a policy's candidates: cand_id, features, rewards, and whether a bank answer says the same."""
    bank = completion.split(corpus.bank(scored.sparkSession)).where("sql is not null").select("question_id", "sql").distinct().withColumn("in_bank", F.lit(True))
    known = scored.join(bank, ["question_id", "sql"], "left").withColumn("in_bank", F.coalesce("in_bank", F.lit(False)))
    return policy.featurise(known).withColumn("cand_id", F.col("rollout_id"))


def within_schema(cands: DataFrame, questions: DataFrame, columns: DataFrame, references: DataFrame | None = None, keep: int = 30, scorer: str = "tfidf") -> DataFrame:
    """Candidates that name no column of their database beyond the ``keep`` best ranked for the question (and keys)."""
    kept = schema_filter.rank(questions, columns, keep, scorer, references).groupBy("question_id").agg(F.collect_set("column_name").alias("kept"))
    known = columns.groupBy("db_id").agg(F.collect_set("column_name").alias("known"))  # a schema's columns, as many as it declares
    used = F.array_intersect(F.regexp_extract_all(F.lower(F.coalesce("sql", F.lit(""))), F.lit("[a-z0-9_]+"), 0), F.col("known"))
    joined = cands.join(kept, "question_id").join(known, "db_id").where(F.size(F.array_except(used, F.col("kept"))) == 0)
    return joined.drop("kept", "known")


def infer(spark: SparkSession, sf_dir: str, tier: str = "s", k: int = 30, temperature: float = 1.0, keep: int = 30) -> DataFrame:
    """(question_id, difficulty, rollout_id, share, correct): filter the schema, sample, run and vote.

    A question without any candidate inside the filtered schema counts as wrong.
    """
    questions = corpus.questions(spark)
    parsed = completion.split(corpus.rollouts(spark, k, tier, temperature))
    asked = questions.select("question_id", "db_id", "question")
    judged = execute.judge(spark, sf_dir, within_schema(parsed, asked, schema_columns(spark, sf_dir), schema_references(spark), keep), questions)
    picked = selection.majority(judged)
    every = questions.select("question_id", "difficulty").join(picked, "question_id", "left")
    return every.withColumn("correct", F.coalesce("correct", F.lit(False)))
