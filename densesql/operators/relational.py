"""Generic operators that Spark composes but does not name: as-of, range and top-k joins, samples, fingerprints."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str, tolerance_s: float | None = None) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` at or before its time; one shuffle and sort of the union."""
    at = "_at"
    a = left.withColumns({"_side": F.lit(1), "_row": F.monotonically_increasing_id(), "_v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(by, on, F.col(value).alias("_v")).withColumn("_side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(on, "_side", "_row").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumns({at: F.last(F.when(F.col("_side") == 0, F.struct(on, "_v")), ignorenulls=True).over(w)})
    fresh = F.col(at)["_v"]
    if tolerance_s is not None:
        fresh = F.when(F.col(on).cast("timestamp").cast("double") - F.col(at)[on].cast("timestamp").cast("double") <= tolerance_s, fresh)
    return seen.where("_side = 1").withColumn(f"asof_{value}", fresh).select(*left.columns, f"asof_{value}")


def range_join(left: DataFrame, right: DataFrame, by: str, left_on: str, right_on: str, width_s: int) -> DataFrame:
    """Pairs with ``right_on`` in [left_on, left_on + width]; time buckets make it an equi-join of linear size."""
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / width_s)
    a = left.withColumn("_b", F.explode(F.array(bucket(left_on), bucket(left_on) + 1)))
    b = right.withColumn("_b", bucket(right_on))
    late = F.unix_micros(F.col(right_on).cast("timestamp")) - F.unix_micros(F.col(left_on).cast("timestamp"))
    return a.join(b, [by, "_b"]).where((late >= 0) & (late <= width_s * 1_000_000)).drop("_b")


def top_k_per_key(df: DataFrame, by: list[str], order: list[Column], k: int, rank: str = "rank") -> DataFrame:
    """The first k rows of each key; Spark limits ranks on both sides of the shuffle."""
    return df.withColumn(rank, F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col(rank) <= k)


def salted_join(large: DataFrame, small: DataFrame, on: str, salts: int = 8) -> DataFrame:
    """An equi-join whose hot keys spread over ``salts`` tasks; the other side is repeated."""
    a = large.withColumn("_s", F.pmod(F.xxhash64(*large.columns), F.lit(salts)).cast("int"))
    b = small.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [on, "_s"]).drop("_s")


def hash_sample(df: DataFrame, key: str, n: int, by: str | None = None) -> DataFrame:
    """A repeatable sample: the first n rows (of each stratum) in the order of a digest of their key."""
    digest = F.md5(F.col(key).cast("string").cast("binary"))
    if by is None:
        return df.orderBy(digest, key).limit(n)
    return top_k_per_key(df, [by], [digest, F.col(key)], n, "_r").drop("_r")


def dedup_keep_first(df: DataFrame, by: list[str], order: list[str]) -> DataFrame:
    """One row a key, the first by order, as an aggregate with partial sums and no sort."""
    rest = [c for c in df.columns if c not in by]
    best = F.min_by(F.struct(*rest), F.struct(*order)).alias("_b")
    return df.groupBy(*by).agg(best).select(*by, *[F.col("_b")[c].alias(c) for c in rest])


def fingerprint(df: DataFrame) -> DataFrame:
    """(n, h): equal for equal bags of rows, whatever their order."""
    return df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64(*df.columns).cast("decimal(38,0)")).alias("h"))


def explain_text(df: DataFrame) -> str:
    """The formatted plan, for checks of what a query does."""
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")
