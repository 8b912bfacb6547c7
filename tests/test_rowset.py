"""Rows picked by bitmaps of ids."""

from pyspark.sql import functions as F

from densesql.plans.rowset import picked


def test_picks_exactly_the_rows_of_the_ids(spark):
    df = spark.range(0, 200000, 1, 5).select((F.col("id") % 7 * (1 << 33) + F.col("id")).alias("row_id"), F.col("id").alias("x"))
    ids = df.where("x % 3 = 1 or x in (0, 32767, 32768, 32769)").select("row_id")
    found = picked(df, ids.union(ids), "row_id")
    assert found.columns == ["row_id", "x"]
    assert sorted(r["x"] for r in found.collect()) == [x for x in range(200000) if x % 3 == 1 or x in (0, 32767, 32768, 32769)]
    assert picked(df, ids.where("false"), "row_id").count() == 0
