"""Set joins read each row once, carry a group of similar sets in blocks, and keep wide sets exact."""

import random

import pytest
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.operators import setjoin


def all_pairs(given, t):
    found = {(a, b): len(x & y) / len(x | y) for a, x in given.items() for b, y in given.items() if a < b and x and y}
    return {k: v for k, v in found.items() if v >= t - 1e-9}


def test_items_are_computed_once(spark):
    seen = spark.sparkContext.accumulator(0)

    @F.udf("array<string>")
    def words(n):
        seen.add(1)
        return [f"w{k}" for k in range(n, n + 12)]

    assert setjoin.prefix_join(spark.range(20).withColumn("items", words("id")), "id", "items", 0.8).count() == 19
    assert seen.value == 20


@pytest.mark.parametrize("block, carried, entries", [(setjoin.BLOCK, setjoin.COMPARED, setjoin.ENTRIES), (1500, 15000, 3000)])
def test_wide_sets_equal_all_pairs_and_are_carried_in_blocks(spark, monkeypatch, block, carried, entries):
    for name, value in (("BLOCK", block), ("COMPARED", carried), ("ENTRIES", entries)):
        monkeypatch.setattr(setjoin, name, value)
    rng, given = random.Random(3), {}
    for size in (40, 250, 257, 300, 512, 1025):  # around the widths at which bitmaps begin and grow
        words = [f"{size}-{k}" for k in range(size)]
        for copy in range(12):
            gone = set(rng.sample(words, size * copy // 60))
            given[len(given)] = {w for w in words if w not in gone} | {f"{size}-{copy}-{k}" for k in range(size * (copy % 4) // 40)}
    rows = {}
    table = setjoin.Staging.table

    def counted(self, df, name, row_id=None):
        out = table(self, df, name, row_id)
        rows[name] = out.count()
        return out

    monkeypatch.setattr(setjoin.Staging, "table", counted)
    df = spark.createDataFrame([(k, list(v)) for k, v in given.items()], "id long, items array<string>").repartition(3)
    found = setjoin.prefix_join(df, "id", "items", 0.8).collect()
    want = all_pairs(given, 0.8)
    assert len(found) == len(want) and {(r["left_id"], r["right_id"]): r["overlap"] for r in found} == pytest.approx(want)
    if block > 1500:
        assert rows["scored-carried"] < len(want)  # in pairs it would be twice as many as these at least
    else:
        assert {"likely-1", "scored-1"} <= set(rows)  # in passes


def test_word_sets_are_the_tokens_of_every_letter(spark):
    letters = "".join(chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000)
    texts = [None, "", "--", "A_1 a_1 b"] + [" ".join(f"x{c}y{c}" for c in letters[k : k + 4096]) for k in range(0, len(letters), 4096)]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    want = {r["id"]: r["a"] for r in df.select("id", F.array_distinct(T.tokens(F.col("text"))).alias("a")).collect()}
    assert {r["id"]: r["a"] for r in setjoin.word_sets(df, "id", "text", "a").collect()} == want


def test_nothing_to_join(spark):
    df = spark.createDataFrame([(1, None), (2, []), (3, [None])], "id long, items array<string>")
    assert setjoin.prefix_join(df, "id", "items", 0.8).collect() == setjoin.prefix_join(df.where("id < 0"), "id", "items", 0.8).collect() == []
