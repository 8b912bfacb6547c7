"""Self-BLEU of groups of any size against the plain form."""

import random

import pytest

from densesql.operators import metrics


def test_self_bleu_compares_all_of_a_large_group(spark):
    rng = random.Random(3)
    texts = {"large": [" ".join(rng.choice("abcdefgh") for _ in range(rng.randrange(0, 14))) for _ in range(150)], "one": ["a b"], None: ["A b c d e", "a b c d"]}
    df = spark.createDataFrame([(g, t) for g, ts in texts.items() for t in ts], "g string, trace string").repartition(5)
    found = {r["g"]: (r["k"], r["self_bleu"]) for r in metrics.self_bleu(df, "g").collect()}
    assert found.keys() == texts.keys()
    for g, ts in texts.items():
        assert found[g] == (len(ts), pytest.approx(metrics.self_bleu_of([t.lower().split() for t in ts])))


def test_passes_of_self_bleu_are_bounded_and_change_nothing(spark, monkeypatch):
    rng = random.Random(4)
    texts = {g: [" ".join(rng.choice("abcdef") for _ in range(rng.randrange(0, 12))) for _ in range(20)] for g in ("x", "y", "")} | {None: ["a b c", "a b c d"]}
    df = spark.createDataFrame([(g, t) for g, ts in texts.items() for t in ts], "g string, trace string").repartition(3)
    written, table = [], metrics.Staging.table

    def counted(self, df, name, row_id=None):
        written.append(name)
        return table(self, df, name, row_id)

    monkeypatch.setattr(metrics.Staging, "table", counted)
    monkeypatch.setattr(metrics, "BLEU_PASS", sum(len(t.split()) for ts in texts.values() for t in ts) // 2 + 1)
    found = {r["g"]: (r["k"], r["self_bleu"]) for r in metrics.self_bleu(df, "g").collect()}
    assert found == {g: (len(ts), pytest.approx(metrics.self_bleu_of([t.split() for t in ts]))) for g, ts in texts.items()}
    assert sorted(written) == ["hits-1-0", "hits-1-1", "hits-2-0", "hits-2-1", "hits-3-0", "hits-3-1", "hits-4-0", "hits-4-1", "rows"]
