"""Advantages, losses, the supervised stage and training of the stand-in policy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.operators import corpus, grpo, metrics, policy, rewards, sft, training
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.queries.rewards import scored
from densesql.queries.training import candidates
from densesql.sources.tables import table

_REWARDS = "g as (select user_id as question_id, event_id as rollout_id, value as total from events)"


def grouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as rollouts of their user, rewarded with their value."""
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("question_id"), F.col("event_id").alias("rollout_id"), F.col("value").alias("total"))


@query(
    "grpo_advantage",
    f"""with {_REWARDS}, s as (select *, avg(total) over w as m, stddev_pop(total) over w as s from g window w as (partition by question_id))
    select question_id, rollout_id, round(case when s > 0 then (total - m) / (s + 1e-6) else 0 end, 6) as advantage from s""",
)
def grpo_advantage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grpo.advantages(grouped(spark, sf_dir)).select("question_id", "rollout_id", F.round("advantage", 6).alias("advantage"))


@query(
    "grpo_mean_only",
    f"with {_REWARDS} select question_id, rollout_id, round(total - avg(total) over (partition by question_id), 9) as advantage from g",
)
def grpo_mean_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grpo.advantages(grouped(spark, sf_dir), normalise=False).select("question_id", "rollout_id", F.round("advantage", 9).alias("advantage"))


@query("grpo_value_baseline")
def grpo_value_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The critic contrast: reward variance before and after taking off a fitted value."""
    found = grpo.value_advantages(candidates(spark, sf_dir))
    return found.agg(F.round(F.var_pop("total"), 6).alias("reward_var"), F.round(F.var_pop("advantage"), 6).alias("advantage_var"), F.count(F.lit(1)).alias("n"))


@query(
    "sparse_vs_dense_signal",
    """with g as (select source, case when quality = 1 then 1.0 else 0.0 end as sparse, case when quality = 1 then 1.0 else 0.0 end + n_chars / 100000.0 as dense
        from documents join labels using (doc_id)),
    p as (select source, stddev_pop(sparse) as ss, stddev_pop(dense) as sd, avg(case when sparse > 0 then 1.0 else 0.0 end) as ps, avg(case when dense > 0 then 1.0 else 0.0 end) as pd, count(*) as n from g group by source)
    select 'sparse' as reward, round(sum(ps * n) / sum(n), 6) as rollout_share, round(avg(case when ss > 1e-12 then 1.0 else 0.0 end), 6) as group_share from p
    union all select 'dense', round(sum(pd * n) / sum(n), 6), round(avg(case when sd > 1e-12 then 1.0 else 0.0 end), 6) from p""",
)
def sparse_vs_dense_signal(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "n_chars").join(table(spark, sf_dir, "labels"), "doc_id")
    hit = F.when(F.col("quality") == 1, 1.0).otherwise(0.0)
    both = docs.select(F.col("source").alias("question_id"), hit.alias("sparse"), (hit + F.col("n_chars") / 100000.0).alias("dense"))
    parts = [metrics.signal_density(both, r).select(F.lit(r).alias("reward"), F.round("rollout_share", 6).alias("rollout_share"), F.round("group_share", 6).alias("group_share")) for r in ("sparse", "dense")]
    return parts[0].union(parts[1])


@query("signal_density_rollouts")
def signal_density_rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Zero-advantage groups under the binary and the dense reward, by tier."""
    out = None
    for tier in corpus.TIERS:
        base = scored(spark, sf_dir, tier)
        for name in ("binary", "total"):
            row = metrics.signal_density(base, name).select(F.lit(tier).alias("tier"), F.lit(name).alias("reward"), F.round("rollout_share", 6).alias("rollout_share"), F.round("group_share", 6).alias("group_share"))
            out = row if out is None else out.union(row)
    return out


@query(
    "surrogate_loss",
    """with e as (select user_id, event_id, value, event_id % 7 as k from events),
    a as (select *, (value - avg(value) over w) / (stddev_pop(value) over w + 1e-6) as adv, -(1 + value) / 100 as old_logp, -(1 + value + k - 3) / 100 as logp from e window w as (partition by user_id)),
    r as (select adv, exp(logp - old_logp) as ratio, exp(old_logp - logp) - (old_logp - logp) - 1 as kl from a)
    select round(-avg(least(ratio * adv, least(greatest(ratio, 0.98), 1.02) * adv)), 6) as clipped,
        round(-avg(least(ratio * adv, least(greatest(ratio, 0.98), 1.02) * adv) - 0.1 * kl), 6) as penalised from r""",
)
def surrogate_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("question_id"), F.col("value").alias("total"), (F.col("event_id") % 7).alias("k"))
    a = grpo.advantages(e).withColumns({"old_logp": -(1 + F.col("total")) / 100, "logp": -(1 + F.col("total") + F.col("k") - 3) / 100})
    a = a.withColumn("ref_logp", F.col("old_logp"))
    plain, held = grpo.loss(a, 0.02), grpo.loss(a, 0.02, 0.1)
    return plain.select(F.round("loss", 6).alias("clipped")).crossJoin(held.select(F.round("loss", 6).alias("penalised")))  # one row each


_LOGP = """
l as (select user_id, list(-(1 + value) / 100 order by ts, event_id) as lp from events group by user_id)
"""


def _with_logp(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    held = F.array_sort(F.collect_list(F.struct("ts", "event_id", (-(1 + F.col("value")) / 100).alias("lp"))))
    return e.groupBy("user_id").agg(F.transform(held, lambda x: x["lp"]).alias("token_logp")).withColumn("n_prompt", F.lit(3))


@query("completion_nll", f"with {_LOGP} select user_id, round(-coalesce(list_sum(lp[4:]), 0), 6) as nll, greatest(len(lp) - 3, 0) as n_tokens from l")
def completion_nll(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = sft.completion_nll(_with_logp(spark, sf_dir))
    return found.select("user_id", F.round("nll", 6).alias("nll"), F.col("n_tokens").cast("long").alias("n_tokens"))


@query("full_nll", f"with {_LOGP} select user_id, round(-list_sum(lp), 6) as nll, len(lp) as n_tokens from l")
def full_nll(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = sft.completion_nll(_with_logp(spark, sf_dir), mask_prompt=False)
    return found.select("user_id", F.round("nll", 6).alias("nll"), F.col("n_tokens").cast("long").alias("n_tokens"))


@query(
    "ngram_mle",
    """with t as (select list_concat(['<s>'], regexp_extract_all(lower(text), '[a-z0-9_]+'), ['</s>']) as t from benchmark),
    g as (select t[i] as context, t[i + 1] as token, count(*) as n from (select t, unnest(range(1, len(t))) as i from t) group by 1, 2),
    v as (select count(distinct token) as words from g)
    select context, token, n, round(ln((n + 0.1) / (sum(n) over (partition by context) + 0.1 * words)), 6) as logp from g, v""",
)
def ngram_mle(spark: SparkSession, sf_dir: str) -> DataFrame:
    model = sft.fit_ngram(table(spark, sf_dir, "benchmark"), "text", order=2)
    return model.select("context", "token", "n", F.round("logp", 6).alias("logp"))


@query("ngram_corpus_size")
def ngram_corpus_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """More bank, better fit: held-out loss of the n-gram model by the number of seeds it was counted on."""
    staging = Staging(spark, "ngram")
    full = staging.table(corpus.bank(spark, 6), "bank")
    held = full.where("seed = 5").withColumn("key", F.col("question_id") * 10 + F.when(F.col("teacher") == "plan", 1).when(F.col("teacher") == "story", 2).when(F.col("teacher") == "clauses", 3).otherwise(4))
    out = None
    for seeds in (1, 2, 5):
        model = staging.table(sft.fit_ngram(full.where(F.col("seed") < seeds), "completion", 3), f"model-{seeds}")
        per = sft.score(held, model, "key", "completion", 3).agg(F.lit(seeds).alias("seeds"), F.round(F.sum("nll") / F.sum("n_tokens"), 6).alias("per_token"))
        out = per if out is None else out.union(per)
    return out


@query(
    "expected_return",
    """with r as (select conv_id, sum(length(text) / 1000.0 * pow(0.9, turn)) as ret from conversations group by conv_id)
    select count(*) as n, round(avg(ret), 6) as mean_return, round(stddev_pop(ret), 6) as std_return from r""",
)
def expected_return(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations as episodes: discounted returns."""
    e = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("episode_id"), F.col("turn").alias("t"), (F.length("text") / 1000.0).alias("reward"))
    found = grpo.expected_return(e, 0.9)
    return found.select("n", F.round("mean_return", 6).alias("mean_return"), F.round("std_return", 6).alias("std_return"))


# --- training


@query("memory_weight_concentration")
def memory_weight_concentration(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Result entropy of what a policy samples as the memory term grows: the pull toward stored patterns."""
    cands = candidates(spark, sf_dir)
    theta, rows = np.zeros(len(policy.FEATURES)), []
    for w in (0.0, 1.0, 4.0):
        learned = training.train(rewards.compose(cands, (1, 1, 1, w)), theta, Staging(spark, "weights"), "run", steps=500, every=500)[-1]["theta"]
        known = grpo.with_probabilities(cands, learned)
        per = known.where("result is not null").groupBy("question_id", "result").agg(F.sum("prob").alias("p"))
        share = per.withColumn("p", F.col("p") / F.sum("p").over(Window.partitionBy("question_id")))
        entropy = share.groupBy("question_id").agg((-F.sum(F.col("p") * F.log("p"))).alias("h")).agg(F.avg("h")).first()[0]
        rows.append((w, round(entropy, 6)))
    return spark.createDataFrame(rows, "memory_weight double, entropy double")


@query("sampler_frequencies")
def sampler_frequencies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frequencies of Gumbel draws against softmax probabilities on four candidates."""
    rows = [(1, k, [float(x)]) for k, x in enumerate((0.0, 0.5, 1.0, 2.0))]
    cands = spark.createDataFrame(rows, "question_id long, cand_id int, x array<double>")
    drawn = grpo.sample(cands, np.array([1.0]), group=4000, seed=5)
    known = grpo.with_probabilities(cands, np.array([1.0])).select("cand_id", "prob")
    seen = drawn.groupBy("cand_id").agg((F.count(F.lit(1)) / 4000).alias("share"))
    return known.join(seen, "cand_id").select("cand_id", F.round("prob", 6).alias("prob"), F.round("share", 6).alias("share"))
