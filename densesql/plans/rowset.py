"""Rows picked from a large table by their ids, without a shuffle of the table.

Ids that lie close together, as those of staged rows do, take about a bit each in
bitmaps of 32768: they are built on the executors and broadcast, and the table is read
once where it lies.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def picked(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """The rows of ``df`` whose ``key`` (a long from 0 on, the same column in both) is among ``ids``, which may repeat."""
    marks = ids.groupBy(F.bitmap_bucket_number(key).alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(key)).alias("_bits"))
    at = F.bitmap_bit_position(key)
    byte = F.conv(F.hex(F.substring(F.col("_bits"), F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = F.call_function("shiftright", byte, F.pmod(at, F.lit(8)).cast("int")).bitwiseAND(F.lit(1)) == 1
    joined = df.join(F.broadcast(marks), F.bitmap_bucket_number(df[key]) == F.col("_bucket"))
    return joined.where(hit).select(*df.columns)
