"""Preference pairs and their loss over every pair."""

import math

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as contract
from densesql.operators import baselines


def test_preferences_keep_every_pair(spark):
    given = [(q, k, k % 3 == 0, -((7 * k + q) % 11) / 10) for q in range(3) for k in range(20)]
    df = spark.createDataFrame(given, "question_id int, rollout_id int, correct boolean, logp double")
    margins = [g[3] - b[3] for g in given for b in given if g[0] == b[0] and g[2] and not b[2]]
    assert baselines.preference_pairs(df).count() == len(margins)
    row = baselines.preference_loss_whole(df).first()
    assert (row["n"], row["loss"]) == (len(margins), pytest.approx(sum(math.log1p(math.exp(-0.1 * m)) for m in margins) / len(margins)))


def test_preference_queries_take_every_labelled_document(spark, sf_dir):
    queries = contract.queries()
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    sizes = docs.join(labels, "doc_id").groupBy("source").agg(F.count_if(F.expr("quality = 1")).alias("a"), F.count_if(F.expr("quality != 1")).alias("b"))
    want = sizes.agg(F.sum(F.col("a") * F.col("b"))).first()[0]
    assert queries["preference_pairs"](spark, sf_dir).count() == queries["preference_loss"](spark, sf_dir).first()["n"] == want
