"""Observable features of candidates, the supervised start, sampling for inference, checkpoints."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.operators import grpo

FEATURES = ("bias", "parsed", "format", "joins", "filters", "nesting", "trace_tokens", "diversity", "memory", "logp", "plan", "story", "clauses")


def featurise(scored: DataFrame) -> DataFrame:
    """Add ``x`` from what is seen without the gold; needs ops, trace, style, format_ok, parsed, logp and mem_score."""
    scored = scored.withColumn("_toks", T.tokens(F.col("trace")))  # a column of its own, so that it is computed once
    toks = F.col("_toks")
    kinds = lambda *names: F.size(F.filter("ops", lambda o: o["kind"].isin(*names))).cast("double")
    flag = lambda c: c.cast("double")
    return scored.withColumn(
        "x",
        F.array(
            F.lit(1.0), flag(F.col("parsed")), flag(F.col("format_ok")), kinds("from.join") / 4, kinds("where.condition", "having.condition") / 4,
            kinds("subquery.begin") / 2, F.least(F.log1p(F.size(toks).cast("double")) / 8, F.lit(1.0)), T.diversity(toks), F.coalesce("mem_score", F.lit(0.0)),
            F.coalesce("logp", F.lit(0.0)), flag(F.col("style") == "plan"), flag(F.col("style") == "story"), flag(F.col("style") == "clauses"),
        ),
    ).drop("_toks")


def fit_supervised(cands: DataFrame, target: str = "in_bank", epochs: int = 10, lr: float = 0.5) -> np.ndarray:
    """Weights that raise the likelihood of the bank's candidates; one aggregate an epoch."""
    n = cands.select(F.max(F.size("x"))).first()[0]
    theta = np.zeros(n)
    for _ in range(epochs):
        known = grpo.with_probabilities(cands, theta)
        weight = F.col(target).cast("double") / F.greatest(F.sum(F.col(target).cast("double")).over(grpo.by_question()), F.lit(1.0))
        part = known.withColumn("w", weight - F.when(F.max(target).over(grpo.by_question()), F.col("prob")).otherwise(0.0))
        row = part.agg(*[F.sum(F.col("w") * F.get("x", F.lit(i))).alias(f"g{i}") for i in range(n)], F.countDistinct("question_id").alias("q")).first()
        theta += lr * np.array([row[f"g{i}"] or 0.0 for i in range(n)]) / max(1, row["q"])
    return theta


def save(spark: SparkSession, path: str, step: int, theta: np.ndarray, measures: dict) -> None:
    """One checkpoint below its own step; saving a step again replaces it."""
    row = [(step, [float(t) for t in theta], json.dumps(measures))]
    spark.createDataFrame(row, "step int, theta array<double>, measures string").coalesce(1).write.mode("overwrite").parquet(f"{path}/step={step}")


def load(spark: SparkSession, path: str, step: int) -> tuple[np.ndarray, dict]:
    row = spark.read.parquet(f"{path}/step={step}").first()
    return np.array(row["theta"]), json.loads(row["measures"])
