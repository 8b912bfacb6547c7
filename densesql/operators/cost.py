"""Latency, memory, token and price measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def latency(log: DataFrame, by: tuple[str, ...] = (), seconds: str = "seconds", approximate: bool = False) -> DataFrame:
    """(by..., n, total, mean, p50, p95): exact percentiles, or sketches for large logs."""
    at = (lambda p: F.percentile_approx(seconds, F.lit(p), 10_000)) if approximate else (lambda p: F.percentile(seconds, F.lit(p)))
    return log.groupBy(*by).agg(
        F.count(F.lit(1)).alias("n"), F.sum(seconds).alias("total"), F.avg(seconds).alias("mean"), at(0.5).alias("p50"), at(0.95).alias("p95")
    )


def vram_gb(params_b: Column, width: Column, layers: Column, kv_heads: Column, head_dim: Column, context: Column, batch: Column, other: Column) -> Column:
    """Weights, key-value cache and the rest, in GB of 10^9 bytes."""
    return params_b * width + layers.cast("double") * 2 * kv_heads * head_dim * context * width * batch / 1e9 + other


#: Policies as (name, billions of parameters, layers, key-value heads, head dimension), at typical shapes.
MODELS = (("s", 0.5, 24, 2, 64), ("m", 1.5, 28, 2, 128), ("l", 3.0, 36, 2, 128))


def vram_table(spark: SparkSession, contexts: tuple[int, ...] = (2048, 4096, 8192), batch: int = 30, width: int = 2, other: float = 1.5) -> DataFrame:
    """(tier, context, gb)."""
    rows = spark.createDataFrame(list(MODELS), "tier string, params_b double, layers int, kv_heads int, head_dim int")
    each = rows.withColumn("context", F.explode(F.array(*map(F.lit, contexts))))
    col = F.col
    return each.select("tier", "context", vram_gb(col("params_b"), F.lit(width), col("layers"), col("kv_heads"), col("head_dim"), col("context"), F.lit(batch), F.lit(other)).alias("gb"))


def tokens(prompts: DataFrame, text: str, price_per_million: float, by: tuple[str, ...] = (), chars_per_token: float = 4.0) -> DataFrame:
    """(by..., requests, tokens, mean_tokens, cost): estimated from characters."""
    n = F.ceil(F.length(text) / chars_per_token)
    return prompts.groupBy(*by).agg(
        F.count(F.lit(1)).alias("requests"), F.sum(n).alias("tokens"), F.avg(n).alias("mean_tokens"), (F.sum(n) * F.lit(price_per_million / 1e6)).alias("cost")
    )


def verifier(queries: Column, price_per_query: float = 0.24) -> Column:
    return queries * price_per_query


def distillation(bank: DataFrame, price_per_sample: float = 30 / 37_600) -> DataFrame:
    """One row (samples, cost)."""
    return bank.agg(F.count(F.lit(1)).alias("samples"), (F.count(F.lit(1)) * F.lit(price_per_sample)).alias("cost"))
