"""What must not change with size: draws, hot groups, blocks, chains of stages."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from densesql.llm import near_copies, op4_mix, op5_shards, op10_benchmark
from densesql.plans.ranking import prefix_within_groups
from densesql.plans.staging import Staging


def test_inverted_draws_have_the_exact_law():
    rng = np.random.default_rng(1)
    got = np.bincount([op5_shards.by_inversion(rng, 6, 9, 5) for _ in range(20_000)], minlength=6)
    from math import comb

    want = np.array([comb(6, k) * comb(9, 5 - k) / comb(15, 5) for k in range(6)]) * 20_000
    assert ((got - want) ** 2 / want).sum() < 20.5  # the 0.999 quantile of chi-square with 5 degrees of freedom


def test_draws_beyond_the_generator_have_exact_moments():
    rng = np.random.default_rng(2)
    good, bad, drawn = 4 * 10**10, 96 * 10**10, 4 * 10**9
    total = good + bad
    draws = np.array([op5_shards._hypergeometric(rng, good, bad, drawn) for _ in range(400)], dtype=np.float64)
    mean, variance = drawn * good / total, drawn * (good / total) * (bad / total) * ((total - drawn) / (total - 1))
    assert abs(draws.mean() - mean) < 4 * (variance / 400) ** 0.5
    assert 0.75 < draws.var() / variance < 1.3


def test_matrix_has_exact_margins_at_any_size():
    cells = [3 * 10**9, 0, 1, 5 * 10**9 + 7]
    matrix = op5_shards.communication_matrix(cells, 5)
    assert matrix.sum(axis=1).tolist() == cells and matrix.sum(axis=0).tolist() == op5_shards.shard_sizes(sum(cells), 5).tolist()


def test_whole_assignment_is_uniform(spark):
    """Every row is equally likely in every shard: chi-square over seeds of where each of 30 rows goes."""
    docs = spark.createDataFrame([(k, "x") for k in range(30)], "doc_id long, text string").coalesce(1)
    seen = np.zeros((30, 3))
    for seed in range(30):
        for r in op5_shards.assign_shards(docs, shards=3, cells=4, seed=seed).collect():
            seen[r["doc_id"], r["shard"]] += 1
    assert (seen.sum(axis=0) == 300).all()
    assert ((seen - 10) ** 2 / 10).sum() < 100  # 58 degrees of freedom, far in the tail


@pytest.mark.parametrize("threshold", ["-1", "10485760"])
def test_a_hot_group_is_dealt_by_range(spark, threshold):
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    try:
        staging = Staging(spark, "hot")
        rows = spark.range(2_000).select(F.lit("a").alias("grp"), (F.xxhash64("id").bitwiseAND(F.lit((1 << 31) - 1))).alias("u"), "id", F.lit(1).alias("one"))
        ranked = prefix_within_groups(staging.table(rows, "rows"), staging, "grp", "u", ["id"], "one", "before", "place")
        assert sorted(r["place"] for r in ranked.collect()) == list(range(2_000))
        plan = ranked._jdf.queryExecution().executedPlan().toString()
        window = next(part for part in plan.split("Window [") if "_cut" in part.split("\n")[0] and "row_number" in part.split("\n")[0])
        assert "hashpartitioning(grp" in window and "_cut" in window.split("hashpartitioning(grp")[1].split(")")[0]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_blocks_of_a_benchmark_change_nothing(spark):
    words = [f"w{k}" for k in range(60)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, "a  " + "\n".join(words[5:40]) + " z"), (3, "none")], "doc_id long, text string")
    items = [(k, " ".join(words[3 * k : 3 * k + 14])) for k in range(12)]
    bench = spark.createDataFrame(items, "item_id long, text string")

    def found(block):
        got = op10_benchmark.find_overlaps(docs, bench, block_chars=block).collect()
        return sorted((r["doc_id"], [tuple(h) for h in r["hits"]], sorted(r["items"]), [tuple(s) for s in r["spans"]]) for r in got)

    whole = found(1_000_000)
    assert whole == found(150) and whole[0][1] == [(0, 46)] and whole[2][1] == []


def test_pipeline_stages(spark, sf_dir):
    """Each stage on awkward rows keeps the columns, its decisions take effect, and the run ends in token files."""
    given = corpus_pipeline.documents(spark, sf_dir)
    odd = [(None, None, None, None, None), (10**12, "", "en", "a", 0), (10**12 + 1, "x " * 30_000, "en", "a", 60_000)]
    docs = given.limit(120).union(spark.createDataFrame(odd, given.schema)).union(given.limit(3))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = Staging(spark, "stage").table(stage(spark, docs, sf_dir), name)
        assert kept.columns == docs.columns and kept.dtypes == docs.dtypes
        empty = stage(spark, docs.limit(0), sf_dir)
        assert empty.count() == 0 and empty.columns == docs.columns
    wide = docs.withColumns({c: F.lit(1) for c in ("row_id", "fp", "kept", "size", "copy", "hits")})
    assert corpus_pipeline.near_duplicates(spark, wide, sf_dir).columns == wide.columns


def test_pipeline_run_matches_its_stages_by_hand(spark, sf_dir):
    """The files hold the mix of clean, distinct, uncontaminated documents: held against plain restatements on the small table."""
    got = corpus_pipeline.run(spark, sf_dir).collect()
    docs = corpus_pipeline.documents(spark, sf_dir)
    good = corpus_pipeline.op9_quality.keep_good(docs, corpus_pipeline.documents(spark, sf_dir, "labels")).collect()
    sets = {r["doc_id"]: frozenset(near_copies.shingles(r["text"]).tolist()) for r in good}
    root = {d: d for d in sets}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] == sets[b] or 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) > 0:
                low, high = sorted((find(a), find(b)))
                root[high] = low
    single = {d for d in ids if find(d) == d}
    bench = [(str(r["item_id"]), r["text"]) for r in corpus_pipeline.documents(spark, sf_dir, "benchmark").collect()]
    windows = {w for _, t in bench for w, _ in op10_benchmark.windows_of(t)}

    def clean(text):
        joined = b" " + b" ".join(op10_benchmark.words_of(text)) + b" "
        return not any(b" " + w + b" " in joined for w in windows)

    left = docs.where(F.col("doc_id").isin([r["doc_id"] for r in good if r["doc_id"] in single and clean(r["text"])]))
    taken = {r["doc_id"]: (r["taken"], r["size"]) for r in op4_mix.mix(left).collect() if r["taken"]}
    copies = {d: -(-t // s) for d, (t, s) in taken.items()}
    assert sorted(r["doc_id"] for r in got) == sorted(d for d, n in copies.items() for _ in range(n))
    assert sorted(r["start"] for r in got)[0] == 0 and max(r["start"] + r["n_tokens"] for r in got) == sum(r["n_tokens"] for r in got)
