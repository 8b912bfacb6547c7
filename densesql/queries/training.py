"""Workloads on trained policies: every figure comes from checkpoints that the optimiser reached.

Policies start from the supervised fit to the bank, are trained on the train split with the
rewards named, and are measured on what they sample for the dev split (or all questions,
where a workload needs all levels of difficulty).
"""

from __future__ import annotations

from functools import cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.operators import corpus, metrics, pipeline, policy, rewards, training
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.queries.rewards import scored

STEPS, BATCH, EVERY = 2000, 32, 100
ABLATION = {"full": (1, 1, 1, 1), "no memory": (1, 1, 1, 0), "no atomic": (1, 1, 0, 1), "neither": (1, 1, 0, 0)}


@cache
def _candidates(app: str, sf_dir: str, tier: str) -> DataFrame:
    spark = SparkSession.active()
    splits = corpus.questions(spark).select("question_id", "split")
    return Staging(spark, "candidates").table(pipeline.candidate_table(scored(spark, sf_dir, tier)).join(splits, "question_id"), f"cands-{tier}")


def candidates(spark: SparkSession, sf_dir: str, tier: str = "s") -> DataFrame:
    return _candidates(spark.sparkContext.applicationId, sf_dir, tier)


@cache
def _start(app: str, sf_dir: str, tier: str) -> np.ndarray:
    return policy.fit_supervised(candidates(SparkSession.active(), sf_dir, tier).where("split = 'train'"), epochs=5)


@cache
def _checkpoints(app: str, sf_dir: str, tier: str, weights: tuple, shaping: str, reward: str) -> list[dict]:
    spark = SparkSession.active()
    cands = candidates(spark, sf_dir, tier).where("split = 'train'")
    if shaping != "S3":
        cands = cands.withColumn("atomic", rewards.atomic_reward(F.col("overlap"), F.col("correct"), shaping))
    cands = rewards.compose(cands, weights) if weights != ABLATION["full"] or shaping != "S3" else cands
    return training.train(cands, _start(app, sf_dir, tier), Staging(spark, "training"), "run", STEPS, BATCH, EVERY, reward)


def checkpoints(spark: SparkSession, sf_dir: str, tier: str = "s", weights: tuple = ABLATION["full"], shaping: str = "S3", reward: str = "total") -> list[dict]:
    """Checkpoints of one training run, made once for each session, tables and setting."""
    return _checkpoints(spark.sparkContext.applicationId, sf_dir, tier, weights, shaping, reward)


def _rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


@query("policy_train_curve")
def policy_train_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reward, its spread and accuracy of the batches over 2,000 steps of 32 questions, from the supervised start."""
    rows = [("dense", c["step"], round(c["reward"], 6), round(c["spread"], 6), round(100 * c["ex"], 4)) for c in checkpoints(spark, sf_dir) if c["step"]]
    return metrics.curve(spark.createDataFrame(rows, "tier string, step int, reward double, spread double, ex double"), "reward")


@query("steps_sweep")
def steps_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy, pass@k, reward, failures and trace length on the dev split at every hundredth step, by tier."""
    out = None
    for tier in corpus.TIERS:
        at = [("full", c["step"], c["theta"]) for c in checkpoints(spark, sf_dir, tier)]
        drawn = training.sampled(candidates(spark, sf_dir, tier).where("split = 'dev'"), at)
        row = training.measured(drawn).select(F.lit(tier).alias("tier"), "step", "n", "ex", "pass_at_k", "reward", "syntax_errors", "failing", "mean_trace")
        out = row if out is None else out.union(row)
    return _rounded(out, "ex", "pass_at_k", "reward", "syntax_errors", "failing", "mean_trace")


@query("complexity_by_step")
def complexity_by_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy by difficulty and tier before and after training, over all questions."""
    out = None
    for tier in corpus.TIERS:
        found = checkpoints(spark, sf_dir, tier)
        drawn = training.sampled(candidates(spark, sf_dir, tier), [("full", c["step"], c["theta"]) for c in (found[0], found[-1])])
        row = training.measured(drawn, ("variant", "step", "difficulty")).select(F.lit(tier).alias("tier"), "step", "difficulty", "n", "ex", "pass_at_k")
        out = row if out is None else out.union(row)
    return _rounded(out, "ex", "pass_at_k")


@query("stability")
def stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Votes, Self-BLEU of 30 sampled traces a question and execution groups, trained with and without the memory reward, and untrained."""
    out = None
    for tier in corpus.TIERS:
        full, bare = checkpoints(spark, sf_dir, tier), checkpoints(spark, sf_dir, tier, ABLATION["no memory"])
        at = [("untrained", 0, full[0]["theta"]), ("with memory", STEPS, full[-1]["theta"]), ("without memory", STEPS, bare[-1]["theta"])]
        drawn = Staging(spark, "stability").table(training.sampled(candidates(spark, sf_dir, tier), at, 30), f"drawn-{tier}")
        named = drawn.select("question_id", "variant").distinct()
        bleu = metrics.self_bleu(drawn, "question_id").join(named, "question_id").groupBy("variant").agg(F.avg("self_bleu").alias("self_bleu"))
        row = training.measured(drawn, ("variant",)).join(bleu, "variant").select(F.lit(tier).alias("tier"), "variant", "n", "ex", "self_bleu", "groups")
        out = row if out is None else out.union(row)
    return _rounded(out, "ex", "self_bleu", "groups")


@query("reward_ablation_training")
def reward_ablation_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy and syntax errors on the dev split after training without memory, overlap, both, and with the sparse reward, by tier."""
    out = None
    for tier in corpus.TIERS:
        at = [(name, STEPS, checkpoints(spark, sf_dir, tier, w)[-1]["theta"]) for name, w in ABLATION.items()]
        at.append(("binary", STEPS, checkpoints(spark, sf_dir, tier, reward="binary")[-1]["theta"]))
        drawn = training.sampled(candidates(spark, sf_dir, tier).where("split = 'dev'"), at)
        row = training.measured(drawn).select(F.lit(tier).alias("tier"), "variant", "ex", "pass_at_k", "syntax_errors", "failing")
        out = row if out is None else out.union(row)
    found = _rounded(out, "ex", "pass_at_k", "syntax_errors", "failing")
    return metrics.ablation_delta(found.select("tier", "variant", "ex")).join(found.drop("ex"), ["tier", "variant"])


@query("shaping_training")
def shaping_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy on the dev split after training under each shaping of the overlap reward, for the two smaller tiers."""
    out = None
    for tier in ("s", "m"):
        at = [(shaping, STEPS, checkpoints(spark, sf_dir, tier, shaping=shaping)[-1]["theta"]) for shaping in ("S1", "S2", "S3", "S4")]
        drawn = training.sampled(candidates(spark, sf_dir, tier).where("split = 'dev'"), at)
        row = training.measured(drawn).select(F.lit(tier).alias("tier"), F.col("variant").alias("shaping"), "ex", "pass_at_k", "reward")
        out = row if out is None else out.union(row)
    return _rounded(out, "ex", "pass_at_k", "reward")


@query("trace_evolution")
def trace_evolution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of sampled traces by difficulty before and after training."""
    found = checkpoints(spark, sf_dir, "l")
    drawn = training.sampled(candidates(spark, sf_dir, "l"), [("full", c["step"], c["theta"]) for c in (found[0], found[-1])])
    return _rounded(metrics.trace_length(drawn, ("difficulty", "step"), "trace", 800), "mean", "p50", "over").select("difficulty", "step", "n", "mean", "p50", "longest", "over")


@query("trained_checkpoint")
def trained_checkpoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A checkpoint saved, loaded again and sampled greedily: its step, size and accuracy."""
    staging = Staging(spark, "checkpoint")
    last = checkpoints(spark, sf_dir)[-1]
    policy.save(spark, staging.path("saved"), last["step"], last["theta"], {"reward": last["reward"]})
    theta, measures = policy.load(spark, staging.path("saved"), last["step"])
    drawn = training.sampled(candidates(spark, sf_dir), [("full", last["step"], theta)], 1, 0)
    row = training.measured(drawn).select("step", F.lit(len(theta)).alias("weights"), F.lit(round(measures["reward"], 6)).alias("batch_reward"), "n", "ex")
    return _rounded(row, "ex")
