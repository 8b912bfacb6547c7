"""SimHash near-duplicates by covering locality-sensitive hashing.

A fingerprint has 64 bits.  With radius r, every bit position gets a nonzero vector of
r+1 bits and each nonzero vector v gives a table, whose mask keeps the positions whose
vector has an odd inner product with v.  At most r differing positions leave some v
orthogonal to all their vectors, so that pair agrees on the mask of v: every pair
within the radius collides in some table.

Buckets are never expanded into pairs.  Copies share a fingerprint and count once.  A
fingerprint with company in a table then lists the centres half a radius away, with
flips only where that table's mask leaves freedom: two fingerprints that list the same
centre are within the radius, and any pair within it that collided lists one.  A centre
has at most one member per flip, so its group is bounded whatever the data hold.

Defined results: a null, empty or blank text has fingerprint zero, linked like any
other; a null doc_id takes part but never names a component (null if no member has
one); repeated rows give one result row each; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations, repeat

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from densesql.llm.common import documents, map_rows, numbered
from densesql.plans.components import connected_components
from densesql.plans.staging import Staging

BITS, SEED, SHINGLE, RADIUS = 64, 42, 3, 2


def shingle_hashes(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """The hash of every word shingle of a text, repeats included, as big-endian unsigned integers."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, dtype=">u8")
    runs = map(b" ".join, zip(*(words[k:] for k in range(shingle)), strict=False)) if len(words) >= shingle else [b" ".join(words)]
    return np.fromiter(map(xxh64_intdigest, runs, repeat(SEED)), dtype=">u8")


def majority(hashes: np.ndarray) -> int:
    """The unsigned fingerprint of shingle hashes: the bits set in over half of them."""
    if not len(hashes):
        return 0
    ones = np.zeros(BITS, dtype=np.int64)
    for k in range(0, len(hashes), 1 << 16):
        ones += np.unpackbits(hashes[k : k + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes)).view(">u8")[0])


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit SimHash of a text's word shingles."""
    return majority(shingle_hashes(text, shingle))


def masks(radius: int = RADIUS) -> list[int]:
    """The covering masks, one per table, bit 0 lowest."""
    vectors = (1 << (radius + 1)) - 1
    return [sum(1 << i for i in range(BITS) if ((i % vectors + 1) & v).bit_count() % 2) for v in range(1, vectors + 1)]


def signed(x: int) -> int:
    return x - (1 << BITS) if x >> (BITS - 1) else x


def _flips(free: int, half: int) -> list[int]:
    """Every way to flip up to ``half`` of the free positions, none included."""
    at = [i for i in range(BITS) if free >> i & 1]
    return [signed(sum(1 << i for i in chosen)) for n in range(half + 1) for chosen in combinations(at, n)]


def links(prints: DataFrame, fp: str, radius: int = RADIUS) -> DataFrame:
    """Edges (u, v) between distinct fingerprints; their closure joins all pairs within ``radius``."""
    if radius < 2 or radius % 2:
        raise ValueError("the radius must be even and at least 2")
    full = (1 << BITS) - 1
    tables = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(signed(m)).alias("m")) for k, m in enumerate(masks(radius))])
    keyed = prints.select(F.col(fp).alias("fp"), F.inline(tables)).select("fp", "k", F.col("fp").bitwiseAND(F.col("m")).alias("key"))
    crowded = keyed.groupBy("k", "key").agg(F.min("fp").alias("lo"), F.max("fp").alias("hi")).where("lo != hi").select("k", "key")
    company = keyed.join(crowded, ["k", "key"]).groupBy("fp").agg(F.sort_array(F.collect_set("k")).alias("tables"))
    flips = F.array(*[F.array(*map(F.lit, _flips(full ^ m, radius // 2))) for m in masks(radius)])
    ways = F.array_distinct(F.flatten(F.transform("tables", lambda k: F.get(flips, k))))
    centres = company.select("fp", F.explode(ways).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("centre"))
    lowest = F.min("fp").over(Window.partitionBy("centre"))
    return centres.select("fp", lowest.alias("low")).where("fp != low").select(F.col("fp").alias("u"), F.col("low").alias("v")).distinct()


def hex_digits(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _grouped(docs: DataFrame, radius: int, shingle: int, keep: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """(row_id, doc_id, fp, k0, k1, ...) of every row, and (fp, first) with the component's first row."""
    staging = Staging(docs.sparkSession, "simhash")

    def make() -> Callable:
        return lambda ids, texts: [(i, signed(fingerprint(t, shingle))) for i, t in zip(ids, texts, strict=True)]

    printed = staging.table(map_rows(docs, ["doc_id", "text"], "doc_id long, fp long", make, keep), "printed", row_id="row_id")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row_id")).alias("first")
    distinct = staging.table(printed.groupBy("fp").agg(first), "distinct")
    roots = connected_components(links(distinct, "fp", radius), staging)
    rooted = distinct.join(roots, distinct["fp"] == roots["node"])
    named = rooted.join(rooted.groupBy("root").agg(F.min("first").alias("least")), "root").select("fp", F.col("least").alias("first"))
    alone = distinct.join(roots, distinct["fp"] == roots["node"], "left_anti")
    return printed, named.union(alone)


def near_duplicates(docs: DataFrame, radius: int = RADIUS, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp, component_id) for every row."""
    printed, groups = _grouped(docs, radius, shingle)
    return printed.join(groups, "fp").select("doc_id", "fp", F.col("first.doc_id").alias("component_id"))


def keep_one(docs: DataFrame, radius: int = RADIUS, shingle: int = SHINGLE) -> DataFrame:
    """The first row of every group, by doc_id (nulls last), with the columns of ``docs``."""
    own, names = numbered(docs, "doc_id", "text")
    printed, groups = _grouped(own, radius, shingle, tuple(names))
    stays = groups.select("first.row_id").distinct()
    return printed.join(stays, "row_id", "left_semi").select(*[f"k{n}" for n in range(len(names))]).toDF(*docs.columns)


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(documents(spark, sf_dir))
    return found.select("doc_id", hex_digits(F.col("fp")).alias("fingerprint"), "component_id")
