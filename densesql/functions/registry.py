"""The methods as SQL functions.

Scalars are SQL functions that expand into built-in expressions, so they cost what the
column forms cost; the table function parses a statement in Python.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

SCALARS = (
    """atomic_jaccard(a array<string>, b array<string>) returns double
    return case when size(array_union(a, b)) > 0 then size(array_intersect(a, b)) / size(array_union(a, b)) else 0.0D end""",
    """shape_reward(x double, mix double, cap double, power double) returns double return mix * x + (1 - mix) * cap * pow(x, power)""",
    """cosine(a array<double>, b array<double>) returns double
    return coalesce(try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, x) -> s + x),
        sqrt(aggregate(a, 0.0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0.0D, (s, x) -> s + x * x))), 0.0D)""",
    """format_ok(completion string) returns boolean
    return completion rlike '(?s)^<think>.*[^ \\t\\n].*</think>' and trim(substring_index(completion, '</think>', -1)) rlike '(?i)^(select|with)'""",
    """quality_gate(tokens array<string>) returns boolean return size(tokens) between 30 and 2000""",
)


class _Atoms:
    """One row for each operation of a statement."""

    def eval(self, sql: str):
        from densesql.operators.atoms import operations

        for op in operations(sql):
            yield op.kind, op.key, op.scope, op.depth


def register_functions(spark: SparkSession) -> None:
    for text in SCALARS:
        spark.sql(f"create or replace temporary function {text}")
    spark.udtf.register("atoms", udtf(_Atoms, returnType="kind string, key string, scope int, depth int"))
