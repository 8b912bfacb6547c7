"""The compared systems' ideas, on tables where SQL can check them and on the derived corpus."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.operators import baselines, corpus, grpo, metrics, selection, training
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.queries.rewards import scored
from densesql.queries.training import candidates, checkpoints
from densesql.sources.tables import schema_columns, table

_ITEMS = "i as (select item_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) as a from benchmark)"


@query(
    "demo_select_topk",
    f"""with {_ITEMS}, w as (select item_id, len(a) as n, unnest(a) as w from i),
    p as (select x.item_id as question_id, y.item_id as demo_id, count(*) / cast(max(x.n) + max(y.n) - count(*) as double) as overlap from w x join w y on x.w = y.w and x.item_id <> y.item_id group by 1, 2),
    r as (select *, row_number() over (partition by question_id order by round(overlap, 9) desc, demo_id) as rank from p)
    select question_id, demo_id, round(overlap, 6) as overlap, cast(rank as integer) as rank from r where rank <= 3""",
)
def demo_select_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("question_id"), F.col("text").alias("question"))
    return baselines.select_demos(items, items, 3).withColumn("overlap", F.round("overlap", 6))


def _turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations as questions, turns as candidates, words as operations."""
    return table(spark, sf_dir, "conversations").select(
        F.col("conv_id").alias("question_id"), F.col("turn").alias("rollout_id"), F.array_distinct(T.tokens(F.col("text"))).alias("op_keys"), F.length("text").alias("strength")
    )


@query(
    "tournament",
    """with t as (select conv_id as question_id, turn as rollout_id, length(text) as s from conversations),
    w as (select a.question_id, a.rollout_id, count_if(a.s > b.s or (a.s = b.s and a.rollout_id < b.rollout_id)) as wins from t a join t b on a.question_id = b.question_id and a.rollout_id <> b.rollout_id group by 1, 2),
    r as (select *, row_number() over (partition by question_id order by wins desc, rollout_id) as k from w)
    select question_id, rollout_id, wins from r where k = 1""",
)
def tournament(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.tournament(_turns(spark, sf_dir), "strength")


@query(
    "medoid_choice",
    """with t as (select conv_id as question_id, turn as rollout_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) as a from conversations),
    p as (select x.question_id, x.rollout_id, avg(case when len(list_distinct(list_concat(x.a, y.a))) = 0 then 0 else len(list_intersect(x.a, y.a)) / cast(len(list_distinct(list_concat(x.a, y.a))) as double) end) as agreement
        from t x join t y on x.question_id = y.question_id and x.rollout_id <> y.rollout_id group by 1, 2),
    r as (select *, row_number() over (partition by question_id order by round(agreement, 9) desc, rollout_id) as k from p)
    select question_id, rollout_id, round(agreement, 6) as agreement from r where k = 1""",
)
def medoid_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.medoid(_turns(spark, sf_dir)).withColumn("agreement", F.round("agreement", 6))


_PREFER = """
c as (select source as question_id, doc_id as rollout_id, quality = 1 as correct, -n_chars / 1000.0 as logp from documents join labels using (doc_id)),
p as (select g.question_id, g.rollout_id as chosen, b.rollout_id as rejected, g.logp - b.logp as margin from c g join c b on g.question_id = b.question_id and g.correct and not b.correct)
"""


def _labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "n_chars").join(table(spark, sf_dir, "labels"), "doc_id")
    return docs.select(F.col("source").alias("question_id"), F.col("doc_id").alias("rollout_id"), (F.col("quality") == 1).alias("correct"), (-F.col("n_chars") / 1000.0).alias("logp"))


@query("preference_pairs", f"with {_PREFER} select question_id, chosen, rejected, round(margin, 6) as margin from p")
def preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All labelled documents of a source as chosen and rejected; every pair is kept."""
    return baselines.preference_pairs(_labelled(spark, sf_dir)).withColumn("margin", F.round("margin", 6))


@query("preference_loss", f"with {_PREFER} select count(*) as n, round(avg(ln(1 + exp(-0.1 * margin))), 6) as loss from p")
def preference_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The loss over all those pairs, which are never written out."""
    return baselines.preference_loss_whole(_labelled(spark, sf_dir)).withColumn("loss", F.round("loss", 6))


@query(
    "valid_only_pick",
    """with c as (select user_id as question_id, cast(row_number() over (partition by user_id order by ts, event_id) - 1 as integer) as rollout_id, event_type from events)
    select question_id, min_by(rollout_id, struct_pack(a := cast(event_type = 'error' as integer), b := rollout_id)) as rollout_id from c group by 1""",
)
def valid_only_pick(spark: SparkSession, sf_dir: str) -> DataFrame:
    from densesql.queries.selection import log

    return baselines.valid_only(log(spark, sf_dir)).select("question_id", "rollout_id")


@query("repair_rate")
def repair_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy and failures before and after one and three repair rounds."""
    base = scored(spark, sf_dir).select("question_id", "rollout_id", "db_id", "sql", "status", "error_class", "n_rows", "result", "gold_result", "gold_rows", "correct")
    q, cols = corpus.questions(spark), schema_columns(spark, sf_dir)
    out = None
    for rounds in (0, 1, 3):
        found = baselines.repair(spark, sf_dir, base, q, cols, rounds) if rounds else base
        row = found.agg(F.lit(rounds).alias("rounds"), F.round(F.avg((F.col("status") == "runs").cast("double")), 6).alias("running"), F.round(F.avg(F.col("correct").cast("double")), 6).alias("correct"))
        out = row if out is None else out.union(row)
    return out


@query("pipeline_grid")
def pipeline_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = baselines.search_pipelines(scored(spark, sf_dir), corpus.questions(spark))
    return found.withColumn("ex", F.round("ex", 6))


@query("tree_search")
def tree_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.tree_search(spark, sf_dir, corpus.questions(spark), scored(spark, sf_dir)).select("question_id", "visits", F.round("value", 6).alias("value"), "correct")


@query("process_check")
def process_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rule-based step checker's score by outcome."""
    s = scored(spark, sf_dir).withColumn("steps", baselines.step_check(F.col("trace"), F.col("sql")))
    return s.groupBy("correct").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("steps"), 6).alias("steps"))


@query("end_to_end")
def end_to_end(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every selector on every tier and both splits of databases, on draws of the supervised start and of the trained policy."""
    q = corpus.questions(spark)
    out = None
    for tier in corpus.TIERS:
        found = checkpoints(spark, sf_dir, tier)
        for step in (0, found[-1]["step"]):
            theta = found[-1]["theta"] if step else found[0]["theta"]
            drawn = training.sampled(candidates(spark, sf_dir, tier), [("full", step, theta)], 32).withColumn("question_id", F.col("asked"))
            own = grpo.with_probabilities(candidates(spark, sf_dir, tier), theta).select("question_id", "cand_id", "logp")
            pool = Staging(spark, "pool").table(drawn.join(own, ["question_id", "cand_id"]).join(q.select("question_id", "question"), "question_id"), f"pool-{tier}-{step}")
            best = {
                "vote": selection.majority(pool), "logp vote": selection.majority(pool, F.exp("logp")), "memory vote": selection.majority(pool, F.lit(0.1) + F.col("mem_score")),
                "first": selection.single(pool), "best logp": selection.single(pool, "best_logp"), "valid only": baselines.valid_only(pool),
                "unit tests": baselines.unit_test_vote(pool, baselines.shape_tests()), "upper bound": selection.oracle(pool),
            }
            for name, picked in {"medoid": baselines.medoid(pool), "tournament": baselines.tournament(pool, "logp")}.items():
                best[name] = picked.join(pool.select("question_id", "rollout_id", "correct"), ["question_id", "rollout_id"])
            where = q.select("question_id", F.when(F.col("db_id").isin("clicks", "chat", "vectors"), "single table").otherwise("many tables").alias("split"))
            for name, chosen in best.items():
                row = metrics.execution_accuracy(chosen.select("question_id", "correct").join(where, "question_id"), ("split",))
                row = row.select(F.lit(tier).alias("tier"), F.lit(step).alias("step"), F.lit(name).alias("method"), "split", "n", F.round("ex", 6).alias("ex"))
                out = row if out is None else out.union(row)
    return out
