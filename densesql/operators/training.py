"""Training the stand-in policy for many steps, and measuring what its checkpoints sample.

Steps of a policy are sequential, so several of them run in one executor task over the
questions that those steps draw: at most ``steps_per_job * batch`` questions travel to it,
whatever the number of questions.  Only a weight vector a checkpoint comes back.  The
step itself is the clipped objective: candidates are drawn by the policy as it stood at
the step's begin, and ``inner`` updates follow on the same draws.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densesql.operators import grpo, metrics, selection
from densesql.plans.ranking import prefix_within_groups, uniform31
from densesql.plans.staging import Staging

LOG = "step int, theta array<double>, reward double, spread double, ex double"


def group_advantages(rewards: np.ndarray, eps: float = grpo.EPS) -> np.ndarray:
    """Rewards (questions, draws) against their group's mean, over its deviation; zero where a group agrees."""
    centred = rewards - rewards.mean(axis=1, keepdims=True)
    spread = rewards.std(axis=1, keepdims=True)
    return np.where(spread > 0, centred / (spread + eps), 0.0)


def softmax(logits: np.ndarray) -> np.ndarray:
    """Along the last axis; a logit of minus infinity has probability 0."""
    e = np.exp(logits - logits.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def padded(parts: list[np.ndarray], fill: float = 0.0) -> np.ndarray:
    """Arrays of unequal length as one, filled up at their ends."""
    out = np.full((len(parts), max(map(len, parts)), *parts[0].shape[1:]), fill)
    for k, part in enumerate(parts):
        out[k, : len(part)] = part
    return out


def batch_step(
    theta: np.ndarray, start: np.ndarray, x: np.ndarray, rewards: np.ndarray, sizes: np.ndarray, rng: np.random.Generator, group: int, lr: float,
    temperature: float, clip: float, beta: float, inner: int,
) -> tuple[np.ndarray, np.ndarray]:
    """One step over a batch of questions: (new weights, drawn candidates by question).

    ``x`` (questions, candidates, features) and ``rewards`` are padded; ``sizes`` has the candidates of each.
    The gradient of the clipped ratio is zero for draws whose ratio has left the band on the
    side their advantage pushes; ``beta`` weighs the penalty for leaving the ``start`` policy.
    """
    absent = np.arange(x.shape[1]) >= sizes[:, None]
    rows = np.arange(len(x))[:, None]

    def policy(weights: np.ndarray) -> np.ndarray:
        return softmax(np.where(absent, -np.inf, x @ weights / temperature))

    old = policy(theta)
    upto = old.cumsum(axis=1)
    drawn = ((upto / upto[:, -1:])[:, None, :] <= rng.random((len(x), group))[:, :, None]).sum(axis=2)
    gains, seen = group_advantages(rewards[rows, drawn]), x[rows, drawn]
    first = policy(start) if beta else None
    for _ in range(inner):
        p = policy(theta)
        ratio = p[rows, drawn] / old[rows, drawn]
        live = np.where(gains > 0, ratio <= 1 + clip, ratio >= 1 - clip)
        pull = live * gains * ratio / group
        mean_x = (p[:, None, :] @ x)[:, 0]
        slope = (np.tensordot(pull, seen, 2) - pull.sum(axis=1) @ mean_x) / temperature
        if beta:
            lean = np.log(np.where(absent, 1.0, p)) - np.log(np.where(absent, 1.0, first))
            slope -= beta * np.tensordot(p * (lean - (p * lean).sum(axis=1, keepdims=True)), x, 2) / temperature
        theta = theta + lr * slope / len(x)
    return theta, drawn


def clipped_step(
    theta: np.ndarray, start: np.ndarray, features: list[np.ndarray], rewards: list[np.ndarray], rng: np.random.Generator, group: int, lr: float,
    temperature: float, clip: float, beta: float, inner: int,
) -> tuple[np.ndarray, list[np.ndarray]]:
    """``batch_step`` on one array a question."""
    sizes = np.array(list(map(len, features)))
    theta, drawn = batch_step(theta, start, padded(features), padded(rewards), sizes, rng, group, lr, temperature, clip, beta, inner)
    return theta, list(drawn)


def train(
    cands: DataFrame, theta0: np.ndarray, staging: Staging, name: str, steps: int = 2000, batch: int = 32, every: int = 100, reward: str = "total", group: int = 32,
    lr: float = 0.05, temperature: float = 1.0, clip: float = 0.2, beta: float = 0.01, inner: int = 2, seed: int = 0, steps_per_job: int = 2000,
) -> list[dict]:
    """Checkpoints {step, theta, reward, spread, ex} at step 0 and after every ``every`` steps.

    ``cands`` has (question_id, cand_id, x, correct, <reward>).  Questions take a hash-random
    place; step s uses the ``batch`` places from s * batch on, round and round.
    """
    ids = staging.table(cands.select("question_id").distinct(), f"{name}-ids")
    keyed = ids.withColumns({"all": F.lit(0), "u": uniform31(F.col("question_id"), seed=seed), "one": F.lit(1)})
    places = staging.table(prefix_within_groups(keyed, staging, "all", "u", ["question_id"], "one", "ahead", "place").select("question_id", "place"), f"{name}-places")
    n = places.count()
    if not n:
        return []
    theta, out = np.array(theta0, dtype=float), [{"step": 0, "theta": np.array(theta0, dtype=float), "reward": None, "spread": None, "ex": None}]
    narrow = cands.select("question_id", "cand_id", "x", F.col(reward).cast("double").alias("reward"), F.col("correct").cast("double").alias("correct"))
    for begin in range(0, steps, steps_per_job):
        end = min(steps, begin + steps_per_job)
        needed = narrow.join(places, "question_id")
        if (end - begin) * batch < n:
            needed = needed.where(F.pmod(F.col("place") - F.lit(begin * batch), F.lit(n)) < (end - begin) * batch)
        at, origin = theta.tolist(), np.array(theta0, dtype=float).tolist()

        def run(frames: Iterator[pd.DataFrame], begin: int = begin, end: int = end, at: list = at, origin: list = origin) -> Iterator[pd.DataFrame]:
            held = pd.concat(list(frames)).sort_values(["place", "cand_id"])
            places, sizes = np.unique(held["place"].to_numpy(), return_counts=True)
            cuts = np.cumsum(sizes)[:-1]
            x, reward, correct = (padded(np.split(v, cuts)) for v in (np.stack(held["x"].to_numpy()), held["reward"].to_numpy(), held["correct"].to_numpy()))
            own, start = np.array(at), np.array(origin)
            rows = []
            for step in range(begin, end):
                chosen = np.searchsorted(places, (step * batch + np.arange(min(batch, n))) % n)
                rng = np.random.default_rng([seed, step])
                own, drawn = batch_step(own, start, x[chosen], reward[chosen], sizes[chosen], rng, group, lr, temperature, clip, beta, inner)
                if (step + 1) % every == 0 or step + 1 == end:
                    got, right = (v[chosen[:, None], drawn] for v in (reward, correct))
                    rows.append((step + 1, own.tolist(), got.mean(), got.std(), right.mean()))
            yield pd.DataFrame(rows, columns=["step", "theta", "reward", "spread", "ex"])

        found = needed.select("place", "cand_id", "x", "reward", "correct").coalesce(1).mapInPandas(run, LOG).collect()  # one row a checkpoint
        rows = sorted((r.asDict() for r in found), key=lambda r: r["step"])
        theta = np.array(rows[-1]["theta"])
        out += [{**r, "theta": np.array(r["theta"])} for r in rows if r["step"] % every == 0 or r["step"] == steps]
    return out


def sampled(cands: DataFrame, policies: list[tuple[str, int, np.ndarray]], group: int = 30, temperature: float = 1.0, seed: int = 99) -> DataFrame:
    """``group`` draws of every question by each (variant, step, weights): the candidates' columns, rollout_id the draw.

    ``question_id`` becomes a text that names variant, step and question (``asked`` keeps the
    number), so that every measure by question is one by policy and question.
    """
    rows = F.array(*[F.struct(F.lit(v).alias("variant"), F.lit(s).alias("step"), F.array(*map(F.lit, map(float, t))).alias("theta")) for v, s, t in policies])
    plain = cands.drop("logit", "prob", "logp", "variant", "step", "rollout_id")
    each = plain.withColumn("asked", F.col("question_id")).select("*", F.inline(rows))
    each = each.withColumn("question_id", F.concat_ws("|", "variant", "step", "question_id"))
    logit = F.aggregate(F.zip_with("x", "theta", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    known = each.withColumn("logit", logit).drop("theta")
    if temperature == 0:
        keyed = known.withColumn("draw", F.lit(1)).withColumn("key", F.col("logit"))
    else:
        keyed = known.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(group))))
        noise = -F.log(-F.log(grpo.uniform(F.col("question_id"), F.col("draw"), F.col("cand_id"), seed=seed)))
        keyed = keyed.withColumn("key", F.col("logit") / temperature + noise)
    chosen = keyed.groupBy("question_id", "draw").agg(F.max_by("cand_id", F.struct("key", -F.col("cand_id"))).alias("cand_id"))
    drawn = known.join(chosen, ["question_id", "cand_id"]).withColumn("rollout_id", (F.col("draw") - 1).cast("int")).drop("draw", "logit")
    return drawn if temperature else drawn.withColumn("rollout_id", F.explode(F.sequence(F.lit(0), F.lit(group - 1))))


def measured(drawn: DataFrame, by: tuple[str, ...] = ("variant", "step")) -> DataFrame:
    """(by..., n, ex, pass_at_k, reward, failing, mean_trace, groups): accuracy of the vote and what was sampled."""
    named = drawn.select("question_id", *by).distinct()
    votes = selection.majority(drawn).join(named, "question_id").groupBy(*by).agg(F.count(F.lit(1)).alias("n"), (100 * F.avg(F.col("correct").cast("double"))).alias("ex"))
    any_right = selection.oracle(drawn).join(named, "question_id").groupBy(*by).agg((100 * F.avg(F.col("correct").cast("double"))).alias("pass_at_k"))
    spread = metrics.exec_groups(drawn).join(named, "question_id").groupBy(*by).agg(F.avg("groups").alias("groups"))
    rows = drawn.groupBy(*by).agg(
        F.avg("total").alias("reward"), F.avg((F.col("status") == "parse").cast("double")).alias("syntax_errors"), F.avg((F.col("status") != "runs").cast("double")).alias("failing"),
        F.avg(F.length("trace")).alias("mean_trace"),
    )
    return votes.join(any_right, list(by)).join(rows, list(by)).join(spread, list(by))
