"""A training corpus from raw documents: quality, near-duplicates, benchmark, mix, token files.

Each stage takes (spark, docs, sf_dir), works on all rows the one before it kept and
returns the columns of ``documents``; the last returns one row per document of the
token files.  ``run`` writes every stage as Parquet below the shared folder and hands
the next one a fresh read of it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm import near_copies, op3_tokens, op4_mix, op9_quality, op10_benchmark
from densesql.llm.common import documents
from densesql.plans.staging import Staging, StepChain


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that a quality rule rejects go."""
    return op9_quality.keep_good(docs, documents(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (5-word shingles, Jaccard of 0.8 or more) the row with the smallest doc_id stays."""
    return near_copies.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share a window with the benchmark go."""
    return op10_benchmark.drop_contaminated(docs, documents(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; the one at a source's cut ends at the budget."""
    return op4_mix.mixed_rows(docs)


def token_files(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids written in the file format and read back: doc_id, start, n_tokens, ids_crc32."""
    return op3_tokens.token_files(docs)


_CHAIN = StepChain()

#: A stage's result is written before the next one begins, which then drops what the earlier one had staged.
STAGES = [
    ("quality_rules", _CHAIN.step(quality_rules)),
    ("simhash_near_dedup", _CHAIN.step(near_duplicates)),
    ("benchmark_decontamination", _CHAIN.step(decontaminate)),
    ("mix_to_targets", _CHAIN.step(mix_sources)),
    ("token_files", _CHAIN.step(token_files)),
]

#: The stages use xxHash shingles and a tokenizer, which SQL cannot express; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "pipeline")
    docs = documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = staging.table(stage(spark, docs, sf_dir), name)
    return docs
