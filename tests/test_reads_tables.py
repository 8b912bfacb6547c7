"""Queries whose input grows with the given tables."""

import pytest

import __spark_entry__ as contract

QUERIES = contract.queries()
READERS = {
    "atomic_reward_sql": "events",
    "distillation_cost": "documents",
    "format_reward_literals": "conversations",
    "ngram_baseline": "conversations",
    "op_diff_by_kind": "events",
    "op_options_variants": "events",
    "op_vocabulary": "events",
    "prompts": "conversations",
    "reward_separation": "lineitem",
    "reward_total": "lineitem",
}


@pytest.mark.parametrize("name", sorted(READERS))
def test_query_reads_a_given_table(spark, sf_dir, name):
    df = QUERIES[name](spark, sf_dir)
    assert df.count() > 0 and any(f"/{READERS[name]}.parquet" in f for f in df.inputFiles())
