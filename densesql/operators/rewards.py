"""The composite reward and its baselines, as column expressions over judged rollouts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from densesql.functions.similarity import SHAPES, jaccard, shape, shape_at_one
from densesql.functions.text import ngrams, tokens

COMPONENTS = ("format", "exec", "atomic", "mem")


def format_reward(format_ok: Column) -> Column:
    return F.when(format_ok, 1.0).otherwise(0.0)


def exec_reward(status: Column, correct: Column, scheme: str = "graded") -> Column:
    """``graded``: 0 fails, 1 runs, 2 equals gold.  ``binary``: 1 equals gold, else 0."""
    if scheme == "binary":
        return F.when(correct, 1.0).otherwise(0.0)
    return F.when(correct, 2.0).when(status == "runs", 1.0).otherwise(0.0)


def atomic_reward(overlap: Column, correct: Column, shaping: str | tuple[float, float, float] = "S3", only_wrong: bool = True) -> Column:
    """Shaped overlap; 0 for a correct query unless ``only_wrong`` is off."""
    shaped = shape(overlap, *(SHAPES[shaping] if isinstance(shaping, str) else shaping))
    return F.when(correct, 0.0).otherwise(shaped) if only_wrong else shaped


def compose(df: DataFrame, weights: tuple[float, float, float, float] = (1, 1, 1, 1), gate: str = "hard") -> DataFrame:
    """Add ``total`` from columns format, exec, atomic and mem; a hard gate zeroes malformed rollouts."""
    total = sum((F.col(c) * float(w) for c, w in zip(COMPONENTS, weights, strict=True)), F.lit(0.0))
    return df.withColumn("total", F.when(F.col("format") == 0, 0.0).otherwise(total) if gate == "hard" else total)


def check_separation(shaping: str | tuple[float, float, float] = "S3") -> bool:
    """Whether every wrong total stays below a correct one's 4: format 1, runs 1, memory 1 and the largest shaped value."""
    return 3 + shape_at_one(shaping) < 4


def quality_class(format_ok: Column, status: Column, correct: Column, overlap: Column) -> Column:
    return (
        F.when(~format_ok, "0 wrong format")
        .when(correct, "5 correct")
        .when(status == "parse", "1 unparsable")
        .when(status != "runs", "2 fails")
        .when(overlap < 0.5, "3 wrong, low overlap")
        .otherwise("4 wrong, high overlap")
    )


def scaling_report(scored: DataFrame) -> DataFrame:
    """(class, n, mean of each component and of the total)."""
    cls = quality_class(F.col("format_ok"), F.col("status"), F.col("correct"), F.col("overlap"))
    return scored.groupBy(cls.alias("class")).agg(F.count(F.lit(1)).alias("n"), *[F.avg(c).alias(c) for c in (*COMPONENTS, "total")])


# --- baselines


def ngram_jaccard(a: Column, b: Column, n: int = 2) -> Column:
    """Surface overlap: distinct token n-grams of two texts."""
    return jaccard(ngrams(tokens(a), n), ngrams(tokens(b), n))


def edit_ratio(a: Column, b: Column) -> Column:
    size = F.greatest(F.length(a), F.length(b))
    return F.when(size > 0, F.lit(1.0) - F.levenshtein(a, b) / size).otherwise(1.0)


def partial_baseline(sql: Column, gold: Column, ops: Column, gold_ops: Column, parsed: Column, correct: Column) -> Column:
    """Partial rewards: schema items, syntax, n-grams and execution, up to 4."""
    items = lambda o: F.filter(o, lambda k: F.rlike(k, F.lit("^(rel|join_rel|out_col|key_eq|bucket)\\(")))
    return jaccard(items(ops), items(gold_ops)) + F.when(parsed, 1.0).otherwise(0.0) + ngram_jaccard(sql, gold) + F.when(correct, 1.0).otherwise(0.0)


def coarse_baseline(format_ok: Column, status: Column, correct: Column, trace: Column, most_chars: int = 2000) -> Column:
    """Coarse signals: layout, execution, result and length."""
    flags = (format_ok, status == "runs", correct, F.length(trace) <= most_chars)
    return sum((F.when(f, 1.0).otherwise(0.0) for f in flags), F.lit(0.0))
