"""Set overlap and reward shaping as expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Shaping settings as (mix, cap, power); S3 is the default.
SHAPES = {"S1": (0.15, 1.0, 0.35), "S2": (0.30, 0.85, 0.55), "S3": (0.05, 0.79, 0.20), "S4": (0.60, 0.50, 0.98)}


def jaccard(a: Column, b: Column) -> Column:
    """Overlap of two arrays as sets; 0 where both are empty or null."""
    a, b = (F.coalesce(x, F.slice(F.coalesce(a, b), 1, 0)) for x in (a, b))
    union = F.size(F.array_union(a, b))
    return F.when(union > 0, F.size(F.array_intersect(a, b)) / union).otherwise(F.lit(0.0))


def jaccard_bag(a: Column, b: Column) -> Column:
    """Overlap of two arrays as multisets: shared copies over all copies."""
    keys = F.array_union(a, b)
    count = lambda arr, k: F.size(F.filter(arr, lambda x: x == k))
    low = F.aggregate(keys, F.lit(0), lambda s, k: s + F.least(count(a, k), count(b, k)))
    high = F.aggregate(keys, F.lit(0), lambda s, k: s + F.greatest(count(a, k), count(b, k)))
    return F.when(high > 0, low / high).otherwise(F.lit(0.0))


def shape(x: Column, mix: float = 0.05, cap: float = 0.79, power: float = 0.20) -> Column:
    """Concave capped shaping: linear share plus a capped power of the overlap."""
    return F.lit(mix) * x + F.lit(1.0 - mix) * F.lit(cap) * F.pow(x, F.lit(power))


def shape_named(x: Column, name: str) -> Column:
    return shape(x, *SHAPES[name])


def shape_at_one(name_or_params: str | tuple[float, float, float]) -> float:
    """The largest shaped value; below 1 a wrong query can never reach a correct one's total."""
    mix, cap, _ = SHAPES[name_or_params] if isinstance(name_or_params, str) else name_or_params
    return mix + (1 - mix) * cap
