"""Token expressions over text columns and the three trace-quality heuristics."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Gate thresholds: token count, column mentions per token, distinct columns, distinct token pairs.
MIN_TOKENS, MAX_TOKENS, MIN_DENSITY, MIN_DISTINCT, MIN_DIVERSITY = 30, 2000, 0.05, 2, 0.6


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters, digits and underscores."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^a-z0-9_]+"), lambda t: t != "")


def ngrams(toks: Column, n: int) -> Column:
    """Runs of ``n`` tokens, each joined by one blank, repeats kept: shifted copies zipped together, one pass each."""
    whole = F.greatest(F.size(toks) - (n - 1), F.lit(0))
    out = F.slice(toks, 1, whole)
    for k in range(1, n):
        out = F.zip_with(out, F.slice(toks, k + 1, whole), lambda a, b: F.concat(a, F.lit(" "), b))
    return out


def gate_length(toks: Column, lo: int = MIN_TOKENS, hi: int = MAX_TOKENS) -> Column:
    return F.size(toks).between(lo, hi)


def mentions(toks: Column, columns: Column) -> Column:
    """Tokens that name a column."""
    return F.filter(toks, lambda t: F.array_contains(columns, t))


def density(toks: Column, columns: Column) -> Column:
    return F.coalesce(F.try_divide(F.size(mentions(toks, columns)).cast("double"), F.size(toks).cast("double")), F.lit(0.0))


def distinct_mentions(toks: Column, columns: Column) -> Column:
    return F.size(F.array_intersect(toks, columns))


def diversity(toks: Column) -> Column:
    """Distinct consecutive pairs over all pairs; 1 where there is no pair."""
    pairs = ngrams(toks, 2)
    return F.coalesce(F.try_divide(F.size(F.array_distinct(pairs)).cast("double"), F.size(pairs).cast("double")), F.lit(1.0))


def gate_schema(toks: Column, columns: Column, min_density: float = MIN_DENSITY, min_distinct: int = MIN_DISTINCT) -> Column:
    return (density(toks, columns) >= min_density) & (distinct_mentions(toks, columns) >= min_distinct)


def gate_diversity(toks: Column, min_ratio: float = MIN_DIVERSITY) -> Column:
    return diversity(toks) >= min_ratio


def gate_reason(toks: Column, columns: Column) -> Column:
    """The first rule a trace fails, or ``accepted``."""
    return (
        F.when(F.size(toks) < MIN_TOKENS, "short")
        .when(F.size(toks) > MAX_TOKENS, "long")
        .when(density(toks, columns) < MIN_DENSITY, "density")
        .when(distinct_mentions(toks, columns) < MIN_DISTINCT, "distinct")
        .when(diversity(toks) < MIN_DIVERSITY, "diversity")
        .otherwise("accepted")
    )
