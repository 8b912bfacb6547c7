"""Ranks and prefix sums within groups that may hold most of the rows.

A window over a hot group runs in one task.  Here each group is cut into ranges of a
uniform random key, about as many as the square root of its rows: one small window
runs over the ranges' totals and another within each range, so that no task sees
more than about the root of the largest group.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from densesql.plans.staging import Staging

#: The range of the uniform integer that cuts a group.
UNIFORM_BITS = 31


def prefix_within_groups(df: DataFrame, staging: Staging, group: str, uniform: str, order: list[str], amount: str, before: str, rank: str) -> DataFrame:
    """Add ``before`` (sum of ``amount`` over the earlier rows of the group) and ``rank`` (from 0).

    ``uniform`` is an integer in [0, 2**31) that leads the order within a group; ``order``
    breaks its ties.  The group column must not be null.  ``df`` is read three times, so it
    should be a staged table.

    Group sizes are staged, so that their measured size decides how they are joined.  Rows
    are dealt by group and range whatever that join left behind: the window would accept
    rows dealt by group alone, which puts a hot group into one task.
    """
    sizes = df.groupBy(group).agg(F.count(F.lit(1)).alias("_rows"))
    sizes = staging.table(sizes.select(F.col(group).alias("_g"), F.ceil(F.sqrt("_rows")).cast("long").alias("_cuts")), f"sizes-by-{group}")
    cut = df.join(sizes, F.col(group) == F.col("_g")).drop("_g")
    cut = cut.withColumn("_cut", F.shiftright(F.col(uniform).cast("long") * F.col("_cuts"), UNIFORM_BITS)).drop("_cuts")
    totals = cut.groupBy(group, "_cut").agg(F.sum(amount).alias("_sum"), F.count(F.lit(1)).alias("_n"))
    earlier = Window.partitionBy(group).orderBy("_cut").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(
        F.col(group).alias("_g"),
        F.col("_cut").alias("_c"),
        F.coalesce(F.sum("_sum").over(earlier), F.lit(0)).alias("_sum_before"),
        F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_n_before"),
    )
    within = Window.partitionBy(group, "_cut").orderBy(uniform, *order)
    local_before = F.coalesce(F.sum(amount).over(within.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = cut.repartition(group, "_cut").withColumns({before: local_before, rank: F.row_number().over(within) - 1})
    both = ranked.join(totals, (F.col(group) == F.col("_g")) & (F.col("_cut") == F.col("_c")))
    return both.withColumns(
        {before: (F.col(before) + F.col("_sum_before")).cast("long"), rank: (F.col(rank) + F.col("_n_before")).cast("long")}
    ).drop("_g", "_c", "_cut", "_sum_before", "_n_before")


def uniform31(*parts: Column, seed: int) -> Column:
    """A repeatable uniform integer in [0, 2**31) from the given columns."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed).cast("long"), *parts), 64 - UNIFORM_BITS).cast("long")
