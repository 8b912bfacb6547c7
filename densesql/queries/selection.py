"""Votes, picks and accuracy: on the event log with SQL oracles, and on derived candidates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.operators import corpus, metrics, pipeline, selection, training
from densesql.queries import query
from densesql.queries.rewards import scored
from densesql.queries.training import candidates, checkpoints
from densesql.sources.tables import table

LOG = """
c as (select user_id as question_id, cast(row_number() over (partition by user_id order by ts, event_id) - 1 as integer) as rollout_id,
    case when event_type = 'error' then null else event_type end as result, case when event_type = 'error' then 'parse' else 'runs' end as status,
    event_type = 'purchase' as correct, value, ts from events)
"""
_VOTE = """
g as (select question_id, result, count(*) as size, sum({weight}) as weight, min(rollout_id) as first_id, bool_or(correct) as correct from c where result is not null group by 1, 2),
r as (select *, row_number() over (partition by question_id order by round(weight, 9) desc, size desc, first_id {tie}) as k from g),
q as (select question_id, count(*) as n, coalesce(min(case when status <> 'parse' then rollout_id end), min(rollout_id)) as spare from c group by 1)
select q.question_id, coalesce(first_id, spare) as rollout_id, coalesce(size, 0) as size, round(coalesce(size, 0) / cast(n as double), 6) as share, coalesce(correct, false) as correct
from q left join r on r.question_id = q.question_id and k = 1
"""


def log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as candidates: user is the question, order in time the rollout, type the result, purchase correct."""
    from pyspark.sql import Window

    e = table(spark, sf_dir, "events")
    failed = F.col("event_type") == "error"
    return e.select(
        F.col("user_id").alias("question_id"),
        (F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1).alias("rollout_id"),
        F.when(~failed, F.col("event_type")).alias("result"), F.when(failed, "parse").otherwise("runs").alias("status"),
        (F.col("event_type") == "purchase").alias("correct"), "value", "ts", (-F.col("value")).alias("logp"),
    )


def _shown(df: DataFrame) -> DataFrame:
    return df.withColumn("share", F.round("share", 6))


@query("majority_vote", f"with {LOG}, {_VOTE.format(weight='1.0', tie='')}")
def majority_vote(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(selection.majority(log(spark, sf_dir)))


@query("vote_weighted", f"with {LOG}, {_VOTE.format(weight='value', tie='')}")
def vote_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(selection.majority(log(spark, sf_dir), F.col("value")))


@query("vote_tie_break", f"with {LOG}, {_VOTE.format(weight='1.0', tie='desc')}")
def vote_tie_break(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(selection.majority(log(spark, sf_dir), ties="last"))


@query("oracle_pick", f"with {LOG} select question_id, bool_or(correct) as correct from c group by 1")
def oracle_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    return selection.oracle(log(spark, sf_dir))


@query(
    "single_picks",
    f"""with {LOG} select question_id, min_by(rollout_id, rollout_id) as first_id, min_by(rollout_id, struct_pack(a := value, b := rollout_id)) as best_id,
        min_by(rollout_id, struct_pack(a := cast(status = 'parse' as integer), b := rollout_id)) as valid_id from c group by 1""",
)
def single_picks(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = log(spark, sf_dir)
    pick = lambda how, name: selection.single(c, how).select("question_id", F.col("rollout_id").alias(name))
    return pick("first", "first_id").join(pick("best_logp", "best_id"), "question_id").join(pick("first_valid", "valid_id"), "question_id")


@query("vote_incremental")
def vote_incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """After how many candidates the vote can no longer change."""
    return selection.majority_incremental(scored(spark, sf_dir))


_KS = "(values (1), (5), (10), (20), (30), (40), (50)) t(k)"
KS = (1, 5, 10, 20, 30, 40, 50)


@query(
    "pass_at_k_curve",
    f"""with {LOG}, p as (select k, question_id, max(case when correct then 1.0 else 0.0 end) as p from c, {_KS} where rollout_id < k group by 1, 2)
    select k, round(avg(p), 6) as pass_at_k from p group by k""",
)
def pass_at_k_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.pass_at_k(log(spark, sf_dir), KS).select("k", F.round("pass_at_k", 6).alias("pass_at_k"))


@query(
    "pass_at_k_unbiased",
    f"""with {LOG}, n as (select question_id, count(*) as n, cast(count_if(correct) as bigint) as c from c group by 1),
    p as (select k, case when c = 0 then 0.0 when n - c < k then 1.0 else 1 - exp(list_sum(list_transform(range(n - c + 1, n + 1), lambda i: ln(1 - k / cast(i as double))))) end as p from n, {_KS})
    select k, round(avg(p), 6) as pass_at_k from p group by k""",
)
def pass_at_k_unbiased(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.pass_at_k(log(spark, sf_dir), KS, "unbiased").select("k", F.round("pass_at_k", 6).alias("pass_at_k"))


@query("exec_groups", f"with {LOG} select question_id, count(distinct result) as groups from c group by 1")
def exec_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.exec_groups(log(spark, sf_dir))


@query("exec_groups_sketch")
def exec_groups_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.exec_groups(log(spark, sf_dir), approximate=True)


@query(
    "vote_profile",
    f"""with {LOG}, s as (select question_id, result, count(*) as n from c where result is not null group by 1, 2),
    p as (select *, n / cast(sum(n) over (partition by question_id) as double) as p from s)
    select question_id, cast(sum(n) as bigint) as k, count(*) as groups, round(max(p), 6) as top_share, round(-sum(p * ln(p)) + 0.0, 6) as entropy from p group by 1""",
)
def vote_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = metrics.vote_profile(log(spark, sf_dir))
    return found.withColumns({"top_share": F.round("top_share", 6), "entropy": F.round(F.col("entropy") + 0.0, 6)})


@query(
    "syntax_error_rate",
    f"with {LOG} select cast(question_id % 10 as bigint) as tier, count(*) as n, count_if(status = 'parse') as parse, round(avg(case when status = 'parse' then 1.0 else 0.0 end), 6) as rate from c group by 1",
)
def syntax_error_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = log(spark, sf_dir).withColumn("tier", F.col("question_id") % 10)
    return metrics.syntax_error_rate(c, ("tier",)).select("tier", "n", "parse", F.round("rate", 6).alias("rate"))


@query(
    "ex_by_difficulty_cube",
    f"""with {LOG}, s as (select question_id, max(case when correct then 1.0 else 0.0 end) as ok from c group by 1),
    t as (select case question_id % 3 when 0 then 'simple' when 1 then 'moderate' else 'challenging' end as difficulty, case question_id % 2 when 0 then 's' else 'l' end as tier, ok from s)
    select difficulty, tier, count(*) as n, round(100 * avg(ok), 6) as ex from t group by cube (difficulty, tier)""",
)
def ex_by_difficulty_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cube of accuracy on the event log; remainders of the user number are carriers for difficulty and tier here."""
    chosen = selection.oracle(log(spark, sf_dir))
    third = F.col("question_id") % 3
    named = chosen.withColumns(
        {
            "difficulty": F.when(third == 0, "simple").when(third == 1, "moderate").otherwise("challenging"),
            "tier": F.when(F.col("question_id") % 2 == 0, "s").otherwise("l"),
        }
    )
    return metrics.execution_accuracy(named, ("difficulty", "tier"), cube=True).withColumn("ex", F.round("ex", 6))


# --- on derived candidates


@query("candidates_sweep")
def candidates_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of the vote, pass@k and executed statements as the number of candidates grows, one pool a tier for all."""
    out = None
    for tier, k in [(tier, k) for tier in corpus.TIERS for k in KS]:
        part = scored(spark, sf_dir, tier, 1.0, 50).where(F.col("rollout_id") < k)
        ex = metrics.execution_accuracy(selection.majority(part)).select(F.lit(tier).alias("tier"), F.lit(k).alias("k"), F.round("ex", 6).alias("ex"))
        work = part.agg(F.count_distinct("db_id", "sql").alias("executed"))
        row = ex.crossJoin(metrics.pass_at_k(part, (k,)).select(F.round("pass_at_k", 6).alias("pass_at_k"))).crossJoin(work)  # one row each
        out = row if out is None else out.union(row)
    return out


@query("temperature_sweep")
def temperature_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of the vote and pass@k of the trained policy by sampling temperature, every tier: more variety, better votes."""
    out = None
    for tier in corpus.TIERS:
        theta = checkpoints(spark, sf_dir, tier)[-1]["theta"]
        for t in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0):
            drawn = training.sampled(candidates(spark, sf_dir, tier), [("full", 0, theta)], 32, t)
            row = training.measured(drawn).select(F.lit(tier).alias("tier"), F.lit(t).alias("temperature"), F.round("ex", 6).alias("ex"), F.round("pass_at_k", 6).alias("pass_at_k"), F.round("groups", 6).alias("groups"))
            out = row if out is None else out.union(row)
    return out


@query("pipeline_infer")
def pipeline_infer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole inference path with 30 candidates: accuracy by difficulty."""
    return metrics.execution_accuracy(pipeline.infer(spark, sf_dir), ("difficulty",)).withColumn("ex", F.round("ex", 6))
