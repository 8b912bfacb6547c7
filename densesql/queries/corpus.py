"""The trace bank and the worked memory example."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import completion
from densesql.operators import corpus, embed, execute, memory
from densesql.queries import query
from densesql.queries.rewards import scored
from densesql.sources.tables import schema_columns


def _judged_bank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return execute.judge(spark, sf_dir, completion.split(corpus.bank(spark)), corpus.questions(spark))


@query("bank_stats")
def bank_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples and accuracy of every teacher and of the bank; failures are kept."""
    found = corpus.bank_stats(_judged_bank(spark, sf_dir))
    return found.select("teacher", "n", "correct", F.round("accuracy", 6).alias("accuracy"), "tokens", F.round("cost", 6).alias("cost"))


@query("bank_failures_dropped")
def bank_failures_dropped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the opposite rule would lose: bank rows whose statement is wrong, by layout."""
    bank = _judged_bank(spark, sf_dir)
    return bank.groupBy("format_ok", "correct").agg(F.count(F.lit(1)).alias("n"))


@query("corpus_mutators")
def corpus_mutators(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often each mutation occurs, and how often it leaves the result equal to gold."""
    each = scored(spark, sf_dir).select(F.explode("mutators").alias("mutator"), "correct", "format_ok")
    return each.groupBy("mutator").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("correct"), F.count_if("format_ok").alias("well_formed"))


@query("memory_worked_example")
def memory_worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A coherent trace for a failing statement scores high, degenerate traces near zero."""
    question = corpus.QUESTIONS[16]
    traces = {
        "coherent": corpus.render_trace(question[2], question[3], "plan"),
        "markup only": "<div> </div> <br/> <p></p>",
        "answer only": "The answer is 42",
        "looping": "We join the tables again. " * 40,
        "empty": "",
    }
    asked = spark.createDataFrame([(k, n, t) for k, (n, t) in enumerate(traces.items())], "query_id long, name string, trace string")
    bank = _judged_bank(spark, sf_dir).where("correct and format_ok").withColumn("entry_id", 1000 + F.col("question_id") * 10 + F.length("teacher"))
    store = embed.encode(bank, "entry_id", "trace", keep=("entry_id", "db_id"))
    q = embed.encode(asked.withColumn("db_id", F.lit(question[0])), "query_id", "trace", keep=("query_id", "db_id"))
    found = memory.scores(q, memory.lookup(q, store, 20, "cross"), store)
    return asked.join(found, "query_id").select("name", F.round("score", 6).alias("score"))


@query("memory_admit_rollouts")
def memory_admit_rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Admission of verified rollouts into a memory seeded by one teacher: accepted and turned away, by reason."""
    columns = F.array(*[F.lit(r[0]) for r in schema_columns(spark, sf_dir).select("column_name").distinct().orderBy("column_name").collect()])
    bank = _judged_bank(spark, sf_dir).withColumn("verified", F.col("correct") & F.col("format_ok")).withColumn("entry_id", 10**6 + F.col("question_id") * 10 + F.length("teacher"))
    seeded = embed.encode(memory.seed(bank, "plan"), "entry_id", "trace", keep=("entry_id", "db_id"))
    rolls = scored(spark, sf_dir).where("format_ok").withColumn("query_id", F.col("question_id") * 1000 + F.col("rollout_id"))
    rolls = rolls.withColumn("status", F.when(F.col("correct"), "match").otherwise(F.col("status"))).select("query_id", "db_id", "trace", "status")
    coded = embed.encode(rolls, "query_id", "trace", keep=("query_id", "db_id", "trace", "status"))
    _, report = memory.admit(coded, seeded, columns, mode="greedy_in_order")
    return report
