"""Group-relative optimisation of a small stand-in policy.

The policy is a softmax over a question's candidates with linear features.  Rewards and
features are computed once per candidate; a step samples with Gumbel keys from hashes,
takes advantages inside groups, and brings one gradient vector to the driver.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F

from densesql.functions import vec

EPS = 1e-6


def by_question() -> WindowSpec:
    return Window.partitionBy("question_id")


def advantages(scored: DataFrame, reward: str = "total", eps: float = EPS, normalise: bool = True, std: str = "pop") -> DataFrame:
    """Add ``advantage``: the reward against its group's mean, over its deviation unless ``normalise`` is off."""
    mean = F.avg(reward).over(by_question())
    spread = (F.stddev_pop if std == "pop" else F.stddev_samp)(reward).over(by_question())
    centred = F.col(reward) - mean
    value = F.when(F.coalesce(spread, F.lit(0.0)) > 0, centred / (spread + eps)).otherwise(0.0) if normalise else centred
    return scored.withColumn("advantage", value)


def value_advantages(scored: DataFrame, features: str = "x", reward: str = "total", ridge: float = 1e-3) -> DataFrame:
    """The critic contrast: advantage over a linear value function of the features, fitted by normal equations."""
    n = scored.select(F.max(F.size(features))).first()[0] or 0
    at = lambda i: F.get(features, F.lit(i))
    sums = scored.agg(*[F.sum(at(i) * at(j)).alias(f"a{i}_{j}") for i in range(n) for j in range(i, n)], *[F.sum(at(i) * F.col(reward)).alias(f"b{i}") for i in range(n)]).first()
    a = np.zeros((n, n))
    for i in range(n):
        for j in range(i, n):
            a[i, j] = a[j, i] = sums[f"a{i}_{j}"] or 0.0
    w = np.linalg.solve(a + ridge * np.eye(n), np.array([sums[f"b{i}"] or 0.0 for i in range(n)])) if n else np.zeros(0)
    value = vec.dot(F.col(features), F.array(*map(F.lit, map(float, w))))
    return scored.withColumn("value", value).withColumn("advantage", F.col(reward) - F.col("value"))


def surrogate(advantage: Column, logp: Column, old_logp: Column, clip: float = 0.2, beta: float = 0.0, ref_logp: Column | None = None) -> Column:
    """The clipped objective of one sample, negated, with an optional penalty for leaving a reference."""
    ratio = F.exp(logp - old_logp)
    gain = F.least(ratio * advantage, F.least(F.greatest(ratio, F.lit(1 - clip)), F.lit(1 + clip)) * advantage)
    if beta and ref_logp is not None:
        delta = ref_logp - logp
        gain = gain - F.lit(beta) * (F.exp(delta) - delta - 1)
    return -gain


def loss(df: DataFrame, clip: float = 0.2, beta: float = 0.0) -> DataFrame:
    """One row (n, loss) from columns advantage, logp, old_logp (and ref_logp)."""
    ref = F.col("ref_logp") if beta else None
    return df.agg(F.count(F.lit(1)).alias("n"), F.avg(surrogate(F.col("advantage"), F.col("logp"), F.col("old_logp"), clip, beta, ref)).alias("loss"))


def uniform(*parts: Column, seed: int) -> Column:
    """A repeatable uniform in (0, 1)."""
    return (F.pmod(F.xxhash64(F.lit(seed), *parts), F.lit(1 << 53)) + F.lit(0.5)) / float(1 << 53)


def with_probabilities(cands: DataFrame, theta: np.ndarray, temperature: float = 1.0) -> DataFrame:
    """Add logit, prob and logp: a softmax over each question's candidates."""
    logit = vec.dot(F.col("x"), F.array(*map(F.lit, map(float, theta)))) / max(temperature, 1e-9)
    top = F.max("logit").over(by_question())
    z = cands.withColumn("logit", logit).withColumn("_e", F.exp(F.col("logit") - top))
    return z.withColumn("prob", F.col("_e") / F.sum("_e").over(by_question())).withColumn("logp", F.log("prob")).drop("_e")


def sample(cands: DataFrame, theta: np.ndarray, group: int = 32, temperature: float = 1.0, seed: int = 0) -> DataFrame:
    """(question_id, draw, candidate columns...): ``group`` independent draws a question; temperature 0 is the arg-max."""
    if temperature == 0:
        best = with_probabilities(cands, theta)
        first = F.row_number().over(by_question().orderBy(F.desc("logit"), "cand_id"))
        return best.withColumn("_r", first).where("_r = 1").drop("_r").withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(group))))
    known = with_probabilities(cands, theta, temperature)
    keyed = known.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(group))))
    key = F.col("logit") - F.log(-F.log(uniform(F.col("question_id"), F.col("draw"), F.col("cand_id"), seed=seed)))
    columns = [c for c in keyed.columns if c not in ("question_id", "draw")]
    best = F.max_by(F.struct(*columns), F.struct(key.alias("k"), "cand_id")).alias("b")
    return keyed.groupBy("question_id", "draw").agg(best).select("question_id", "draw", "b.*")


def gradient(cands: DataFrame, theta: np.ndarray, group: int, temperature: float, seed: int, reward: str, baseline: str = "group") -> tuple[np.ndarray, dict]:
    """The policy gradient over one batch and its measures; only d numbers reach the driver."""
    n = len(theta)
    known = with_probabilities(cands, theta, temperature)
    mean = known.groupBy("question_id").agg(F.array(*[F.sum(F.col("prob") * F.get("x", F.lit(i))) for i in range(n)]).alias("mean_x"))
    drawn = sample(cands, theta, group, temperature, seed)
    scored = advantages(drawn, reward) if baseline == "group" else value_advantages(drawn, "x", reward)
    joined = scored.join(mean, "question_id")
    parts = [F.avg(F.col("advantage") * (F.get("x", F.lit(i)) - F.get("mean_x", F.lit(i)))).alias(f"g{i}") for i in range(n)]
    row = joined.agg(*parts, F.avg(reward).alias("reward"), F.stddev_pop(reward).alias("spread"), F.avg(F.col("correct").cast("double")).alias("ex")).first()
    return np.array([row[f"g{i}"] or 0.0 for i in range(n)]), {"reward": row["reward"], "spread": row["spread"], "ex": row["ex"]}


def train(cands: DataFrame, theta0: np.ndarray, steps: int = 20, batch: int | None = None, lr: float = 0.5, group: int = 32, temperature: float = 1.0, seed: int = 0, reward: str = "total", baseline: str = "group", decay: float = 0.0) -> tuple[np.ndarray, list[dict]]:
    """Steps of ascent on a staged candidate table (question_id, cand_id, x, correct, rewards).

    ``batch`` questions are taken in hash order for each step (all if None); ``decay`` pulls
    the weights back to where they began.
    """
    theta, log = np.array(theta0, dtype=float), []
    ids = [r[0] for r in cands.select("question_id").distinct().orderBy(F.xxhash64(F.lit(seed), "question_id")).collect()] if batch else []
    for step in range(steps):
        part = cands
        if batch:
            chosen = [ids[(step * batch + k) % len(ids)] for k in range(min(batch, len(ids)))]
            part = cands.where(F.col("question_id").isin(chosen))
        g, measures = gradient(part, theta, group, temperature, seed + step, reward, baseline)
        log.append({"step": step, **measures})
        theta = theta + lr * g - lr * decay * (theta - theta0)
    return theta, log


def expected_return(episodes: DataFrame, gamma: float = 1.0) -> DataFrame:
    """One row (n, mean_return, std_return) from (episode_id, t, reward)."""
    per = episodes.groupBy("episode_id").agg(F.sum(F.col("reward") * F.pow(F.lit(gamma), F.col("t").cast("double"))).alias("ret"))
    return per.agg(F.count(F.lit(1)).alias("n"), F.avg("ret").alias("mean_return"), F.stddev_pop("ret").alias("std_return"))
