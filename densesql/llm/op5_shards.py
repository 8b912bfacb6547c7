"""Uniform shuffle into shards of exact size by a hypergeometric communication matrix.

Rows are dealt to cells.  How many rows each cell sends to each shard is drawn on the
driver from the multivariate hypergeometric law (cells x shards numbers, both
parameters), so that the outcome is distributed as one big uniform shuffle.  Each cell
permutes its rows and sends the first so many to shard 0, the next to shard 1 and so
on; each shard permutes what it received.  Shard sizes differ by one row at most.

Both permutations use ranks by hash-random keys cut into ranges, so neither a cell nor
a shard has to fit one task.  Only ids travel; texts are read again when written.

Defined results: a null text has 0 bytes and checksum 0; null doc_ids and repeated rows
are rows like any other; fewer rows than shards leave some shards empty; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents
from densesql.plans.ranking import prefix_within_groups, uniform31
from densesql.plans.staging import Staging

SHARDS, CELLS, SEED = 24, 256, 20
#: Standard deviations to either side that an inverted law is summed over.
TAILS = 12


def shard_sizes(rows: int, shards: int) -> np.ndarray:
    return np.array([rows // shards + (k < rows % shards) for k in range(shards)], dtype=np.int64)


def communication_matrix(cell_rows: list[int], shards: int, seed: int = SEED) -> np.ndarray:
    """Rows each cell sends to each shard: rows sum to the cells, columns to the exact shard sizes."""
    left = shard_sizes(sum(cell_rows), shards)
    rng = np.random.default_rng(seed)
    matrix = np.zeros((len(cell_rows), shards), dtype=np.int64)
    for i, n in enumerate(cell_rows):
        rest = n
        for j in range(shards):
            others = int(left[j + 1 :].sum())
            matrix[i, j] = _hypergeometric(rng, int(left[j]), others, rest)
            rest -= matrix[i, j]
        left -= matrix[i]
    return matrix


def _hypergeometric(rng: np.random.Generator, good: int, bad: int, drawn: int) -> int:
    """One draw: the number of good ones among ``drawn`` of ``good + bad``, at any size."""
    low, high = max(0, drawn - bad), min(good, drawn)
    if low == high:
        return low
    if good + bad < 10**9:  # the generator's own range
        return int(rng.hypergeometric(good, bad, drawn))
    return by_inversion(rng, good, bad, drawn)


def by_inversion(rng: np.random.Generator, good: int, bad: int, drawn: int) -> int:
    """One hypergeometric draw by inverting the exact law around its mode.

    Neighbouring probabilities have a rational ratio, so weights relative to the mode need no
    factorials.  They are summed over TAILS standard deviations to either side; what lies
    beyond is less than the resolution of the uniform number that is inverted.
    """
    total = good + bad
    low, high = max(0, drawn - bad), min(good, drawn)
    mode = (drawn + 1) * (good + 1) // (total + 2)
    spread = (drawn * (good / total) * (bad / total) * ((total - drawn) / (total - 1))) ** 0.5
    reach = int(TAILS * spread) + TAILS * TAILS
    first, last = max(low, mode - reach), min(high, mode + reach)
    k = np.arange(first, last, dtype=np.float64)
    steps = np.log(good - k) + np.log(drawn - k) - np.log(k + 1) - np.log(bad - drawn + k + 1)
    weights = np.concatenate([[0.0], np.cumsum(steps)])
    chances = np.cumsum(np.exp(weights - weights.max()))
    return first + int(np.searchsorted(chances, rng.random() * chances[-1], side="right"))


def assign_shards(docs: DataFrame, shards: int = SHARDS, cells: int = CELLS, seed: int = SEED) -> DataFrame:
    """(row_id, doc_id, size, text_crc32, shard, slot) for every row."""
    spark = docs.sparkSession
    staging = Staging(spark, "shards")
    body = F.coalesce("text", F.lit("")).cast("binary")
    plain = docs.select("doc_id", (F.octet_length(body) + 8).cast("long").alias("size"), F.crc32(body).alias("text_crc32"))
    rows = staging.table(plain, "rows", row_id="row_id").withColumns(
        {"cell": F.pmod(F.xxhash64(F.lit(seed), "row_id"), F.lit(cells)), "one": F.lit(1), "u1": uniform31(F.col("row_id"), seed=seed + 1)}
    )
    counts = {r["cell"]: r["count"] for r in rows.groupBy("cell").count().collect()}  # one row a cell
    ids = sorted(counts)
    ends = np.cumsum(communication_matrix([counts[c] for c in ids], shards, seed), axis=1).tolist()
    table = spark.createDataFrame([(c, e) for c, e in zip(ids, ends, strict=True)], "c long, ends array<long>")
    permuted = prefix_within_groups(rows, staging, "cell", "u1", ["row_id"], "one", "ahead", "place")
    dealt = permuted.join(F.broadcast(table), F.col("cell") == F.col("c"))  # cells x shards numbers
    shard = F.size(F.filter("ends", lambda e: e <= F.col("place")))
    sent = dealt.select("row_id", "doc_id", "size", "text_crc32", "one", shard.alias("shard"), uniform31(F.col("row_id"), seed=seed + 2).alias("u2"))
    received = staging.table(sent, "received")
    return prefix_within_groups(received, staging, "shard", "u2", ["row_id"], "one", "before", "slot").select(
        "row_id", "doc_id", "size", "text_crc32", "shard", "slot"
    )


def op5_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign_shards(documents(spark, sf_dir)).select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
