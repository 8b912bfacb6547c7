"""The supervised stage: completion losses, and an n-gram model whose counts are its optimum."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from densesql.functions.text import tokens


def nll(logp: Column, n_prompt: Column, mask_prompt: bool = True) -> Column:
    """Negative log-likelihood of the tokens behind the prompt, or of all tokens."""
    kept = F.slice(logp, n_prompt + 1, F.greatest(F.size(logp) - n_prompt, F.lit(0))) if mask_prompt else logp
    return -F.aggregate(kept, F.lit(0.0), lambda s, x: s + x)


def completion_nll(df: DataFrame, logp: str = "token_logp", n_prompt: str = "n_prompt", mask_prompt: bool = True) -> DataFrame:
    """Add ``nll`` and ``n_tokens``."""
    size = F.size(logp) - (F.col(n_prompt) if mask_prompt else 0)
    return df.withColumns({"nll": nll(F.col(logp), F.col(n_prompt), mask_prompt), "n_tokens": F.greatest(size, F.lit(0))})


def _grams(df: DataFrame, text: str, order: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """(keep..., context, token): every token behind its ``order - 1`` predecessors, with start and end marks."""
    marks = F.array(*[F.lit("<s>")] * (order - 1)) if order > 1 else F.array().cast("array<string>")
    padded = df.select(*keep, F.concat(marks, tokens(F.col(text)), F.array(F.lit("</s>"))).alias("t"))
    at = F.explode(F.sequence(F.lit(order), F.size("t"))).alias("i")
    exploded = padded.select(*keep, "t", at)
    return exploded.select(*keep, F.array_join(F.slice("t", F.col("i") - (order - 1), order - 1), " ").alias("context") if order > 1 else F.lit("").alias("context"), F.get("t", F.col("i") - 1).alias("token"))


def fit_ngram(bank: DataFrame, text: str = "completion", order: int = 3, alpha: float = 0.1) -> DataFrame:
    """(context, token, n, logp): smoothed maximum likelihood; counts are summed before the shuffle."""
    counts = _grams(bank, text, order).groupBy("context", "token").agg(F.count(F.lit(1)).alias("n"))
    words = counts.select("token").distinct().count()
    total = F.sum("n").over(Window.partitionBy("context"))
    return counts.withColumn("total", total).select("context", "token", "n", F.log((F.col("n") + alpha) / (F.col("total") + alpha * words)).alias("logp"), "total")


def score(df: DataFrame, model: DataFrame, key: str, text: str = "completion", order: int = 3, alpha: float = 0.1) -> DataFrame:
    """(key, nll, n_tokens, per_token) of texts under a model; unseen tokens get the smoothing mass."""
    words = model.select("token").distinct().count()
    contexts = model.groupBy("context").agg(F.max("total").alias("total"))
    grams = _grams(df, text, order, (key,)).join(model.select("context", "token", "logp"), ["context", "token"], "left").join(contexts, "context", "left")
    floor = F.log(F.lit(alpha) / (F.coalesce("total", F.lit(0)) + alpha * words))
    per = grams.groupBy(key).agg((-F.sum(F.coalesce("logp", floor))).alias("nll"), F.count(F.lit(1)).alias("n_tokens"))
    return per.withColumn("per_token", F.col("nll") / F.col("n_tokens"))
