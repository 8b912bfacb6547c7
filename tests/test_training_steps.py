"""Whole batches of training steps against one question at a time, and statements that several tiers share."""

import numpy as np
from densesql.operators import execute, training


def by_question(theta, start, features, rewards, rng, group, lr, clip, beta):
    """One update, written out for each question."""
    slope, picks = np.zeros_like(theta), []
    for x, r in zip(features, rewards, strict=True):
        p, q = training.softmax(x @ theta), training.softmax(x @ start)
        drawn = rng.choice(len(p), size=group, p=p)
        gain = training.group_advantages(r[drawn][None])[0]
        slope += (gain[:, None] * (x[drawn] - p @ x)).mean(axis=0)
        lean = np.log(p / q)
        slope -= beta * ((p * (lean - p @ lean))[:, None] * x).sum(axis=0)
        picks.append(drawn)
    return theta + lr * slope / len(features), picks


def test_batches_take_the_same_steps_as_single_questions():
    made = np.random.default_rng(3)
    features = [made.normal(size=(n, 4)) for n in (1, 5, 9, 30)]
    rewards = [made.integers(0, 3, len(x)).astype(float) for x in features]
    sizes, start = np.array(list(map(len, features))), made.normal(size=4)
    one = many = start
    for step in range(20):
        one, picks = by_question(one, start, features, rewards, np.random.default_rng(step), 16, 0.1, 0.2, 0.05)
        many, drawn = training.batch_step(many, start, training.padded(features), training.padded(rewards), sizes, np.random.default_rng(step), 16, 0.1, 1.0, 0.2, 0.05, 1)
        assert (np.stack(picks) == drawn).all() and np.allclose(one, many, atol=1e-12)


def test_shared_statements_run_once(spark, sf_dir, monkeypatch):
    ran, chunk = [], execute._run_chunk
    monkeypatch.setattr(execute, "_RAN", {})
    monkeypatch.setattr(execute, "_run_chunk", lambda s, d, rows, *rest: ran.extend(r[1] for r in rows) or chunk(s, d, rows, *rest))
    asked = lambda *sql: spark.createDataFrame([("tpch", s) for s in sql], "db_id string, sql string")
    execute.run_new(spark, sf_dir, asked("select 1", "select 2"))
    found = execute.run_new(spark, sf_dir, asked("select 2", "select 3", "selec 4"))
    assert sorted(ran) == ["selec 4", "select 1", "select 2", "select 3"]
    assert sorted(r["sql"] for r in found.collect()) == sorted(ran)
