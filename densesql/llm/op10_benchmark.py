"""Benchmark decontamination with one Aho-Corasick automaton.

Benchmark items are normalised to words; every run of ten words (a shorter item: all
its words) is a window.  All windows form one automaton whose symbols are words, and
each normalised document is scanned by it once.  Matches give word positions; where a
document has any, positions are mapped to code points of the original text.

A worker builds the automaton from the items, which are read to the driver only below a
stated number of characters: an automaton takes some 130 bytes a character.  A larger
benchmark is cut into blocks by a hash of the item, one automaton and one scan each,
and the matches of the scans are united by document, so that block size changes nothing.

Defined results: a null text, or one without words, has no hits; an item without words
has no window; a null item_id counts as the empty id; items with equal id count once;
repeated documents give one result row each; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterable
from itertools import repeat

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents, map_rows, numbered
from densesql.plans.staging import Staging

# Words of a window, and what a word is made of (after A-Z are lower-cased).
WINDOW = 10
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: Characters of items that one automaton takes, which makes it about 200 MB in a worker.
BLOCK_CHARS = 1_500_000

_ORIGINAL_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
_TABLE = bytes(
    c + 32 if 0x41 <= c <= 0x5A else c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c > 0x7F else 0x20 for c in range(256)
)
_AUTOMATA: dict[str, "Windows"] = {}

HITS = "doc_id long, n_words long, hits array<struct<first:int,last:int>>, items array<string>, spans array<struct<start:int,end:int>>"


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased words of a text, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_TABLE).split()


def windows_of(text: str | None, window: int = WINDOW) -> list[tuple[bytes, int]]:
    """(words joined by blanks, number of words) of every window of an item."""
    words = words_of(text)
    size = min(window, len(words))
    return [(b" ".join(words[k : k + size]), size) for k in range(len(words) - size + 1)] if words else []


def patterns(items: Iterable[tuple[str, str | None]], window: int = WINDOW) -> dict[bytes, tuple[int, list[str]]]:
    """Window -> (its words, ids of the items that have it)."""
    found: dict[bytes, tuple[int, set[str]]] = {}
    for item_id, text in items:
        for joined, size in windows_of(text, window):
            found.setdefault(joined, (size, set()))[1].add(item_id)
    return {k: (n, sorted(ids)) for k, (n, ids) in found.items()}


class Windows:
    """The automaton over the items' windows; a word's symbol is its number, 0 for words that no item has."""

    def __init__(self, items: Iterable[tuple[str, str | None]], window: int = WINDOW):
        import ahocorasick

        self.numbers: dict[bytes, int] = {}
        self.built = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
        for joined, value in patterns(items, window).items():
            self.built.add_word(tuple(self.numbers.setdefault(w, len(self.numbers) + 1) for w in joined.split(b" ")), value)
        if len(self.built):
            self.built.make_automaton()

    def scan(self, words: list[bytes], text: str | None) -> tuple[list[tuple[int, int]], list[str], list[tuple[int, int]]]:
        """Matched word ranges (both ends included), item ids, and the ranges' code points in the text."""
        if not words or not len(self.built):
            return [], [], []
        found = list(self.built.iter(tuple(map(self.numbers.get, words, repeat(0)))))
        if not found:
            return [], [], []
        merged: list[tuple[int, int]] = []
        for first, last in sorted({(at - size + 1, at) for at, (size, _) in found}):
            if merged and first <= merged[-1][1] + 1:
                merged[-1] = (merged[-1][0], max(last, merged[-1][1]))
            else:
                merged.append((first, last))
        places = [m.span() for m in _ORIGINAL_WORD.finditer(text or "")]
        return merged, sorted({i for _, (_, ids) in found for i in ids}), [(places[a][0], places[b][1]) for a, b in merged]


def windows(items: list[tuple[str, str | None]], window: int, key: str) -> Windows:
    """The automaton of a block, built once in each Python worker, which keeps the last one."""
    if key not in _AUTOMATA:
        _AUTOMATA.clear()
        _AUTOMATA[key] = Windows(items, window)
    return _AUTOMATA[key]


def _scan(docs: DataFrame, items: list[tuple[str, str | None]], window: int, carry: tuple[str, ...]) -> DataFrame:
    key = hashlib.sha256(repr((window, sorted(items, key=repr))).encode("utf-8", "surrogatepass")).hexdigest()
    shared = docs.sparkSession.sparkContext.broadcast(items)  # no more than block_chars, or one item

    def make() -> Callable:
        known = windows(shared.value, window, key)

        def step(ids, texts):
            for doc_id, text in zip(ids, texts, strict=True):
                words = words_of(text)
                hits, items, spans = known.scan(words, text)
                yield (
                    doc_id, len(words), [{"first": a, "last": b} for a, b in hits], items, [{"start": a, "end": b} for a, b in spans]
                )

        return step

    return map_rows(docs, ["doc_id", "text"], HITS, make, carry)


def _merge(scans: list[DataFrame], staging: Staging, carry: int) -> DataFrame:
    """One row a document from the scans of several blocks; hits and their spans become unions of ranges."""
    first = scans[0]
    rest = scans[0].select("row_id", "hits", "items", "spans")
    for other in scans[1:]:
        rest = rest.union(other.select("row_id", "hits", "items", "spans"))
    whole = F.transform(
        F.arrays_zip(F.col("hits").alias("h"), F.col("spans").alias("s")),
        lambda x: F.struct(x["h"]["first"].alias("first"), x["h"]["last"].alias("last"), x["s"]["start"].alias("start"), x["s"]["end"].alias("end")),
    )
    listed = rest.where(F.size("hits") > 0).select("row_id", whole.alias("ranges"), "items").groupBy("row_id")
    both = listed.agg(*[F.array_sort(F.flatten(F.collect_list(c))).alias(c) for c in ("ranges", "items")])

    def step(done, x):
        """Ordered ranges, those that share a word or border on each other as one; code points go with their words."""
        last = F.element_at(done, -1)
        wider = F.struct(
            last["first"].alias("first"), F.greatest(x["last"], last["last"]).alias("last"), last["start"].alias("start"), F.greatest(x["end"], last["end"]).alias("end")
        )
        return F.when((F.size(done) > 0) & (x["first"] <= last["last"] + 1), F.concat(F.slice(done, 1, F.size(done) - 1), F.array(wider))).otherwise(F.concat(done, F.array(x)))

    united = staging.table(both.select("row_id", F.aggregate("ranges", F.slice("ranges", 1, 0), step).alias("ranges"), F.array_sort(F.array_distinct("items")).alias("items")), "united")
    part = lambda a, b: F.transform("ranges", lambda x: F.struct(x[a].alias(a), x[b].alias(b)))
    both = united.select("row_id", part("first", "last").alias("hits"), "items", part("start", "end").alias("spans"))
    named = first.select("row_id", *[f"k{n}" for n in range(carry)], "doc_id", "n_words")
    joined = named.join(both, "row_id", "left")
    return joined.withColumns({c: F.coalesce(c, F.array().cast(both.schema[c].dataType)) for c in ("hits", "items", "spans")})


def find_overlaps(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_chars: int = BLOCK_CHARS, carry: tuple[str, ...] = ()) -> DataFrame:
    """(k0, ..., doc_id, n_words, hits, items, spans) for every document."""
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("id"), "text").distinct()
    chars = items.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = -(-chars // block_chars) or 1
    if blocks == 1:
        return _scan(docs, [tuple(r) for r in items.collect()], window, carry)
    staging = Staging(docs.sparkSession, "benchmark")
    own = staging.table(docs, "docs", row_id="scan_row")
    scans = []
    for k in range(blocks):
        part = items.where(F.pmod(F.xxhash64("id", "text"), F.lit(blocks)) == k)
        found = _scan(own, [tuple(r) for r in part.collect()], window, (*carry, "scan_row"))
        scans.append(staging.table(found.withColumnRenamed(f"k{len(carry)}", "row_id"), f"scan-{k}"))
    return _merge(scans, staging, len(carry)).drop("row_id")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows without any hit, with the columns of ``docs``."""
    own, names = numbered(docs, "doc_id", "text")
    found = find_overlaps(own, benchmark, window, block_chars, tuple(names))
    return found.where(F.size("hits") == 0).select(*[f"k{n}" for n in range(len(names))]).toDF(*docs.columns)


def op10_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_overlaps(documents(spark, sf_dir), documents(spark, sf_dir, "benchmark"))
    hit = F.aggregate("hits", F.lit(0).cast("long"), lambda n, x: n + x["last"] - x["first"] + 1)
    return found.select(
        "doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ","), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"),
    )


ORACLE = r"""
with d as (
    select doc_id, row_number() over () as r,
        regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
    from documents
), b as (
    select coalesce(cast(item_id as varchar), '') as item,
        regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
    from benchmark
), bs as (
    select item, least(10, len(w)) as n, unnest(range(1, cast(len(w) - least(10, len(w)) + 2 as bigint))) as i, w from b where len(w) > 0
), bw as (
    select distinct item, n, array_to_string(w[i : i + n - 1], ' ') as win from bs
), ns as (select distinct n from bw
), ds as (
    select r, n, unnest(range(1, cast(len(w) - n + 2 as bigint))) as i, w from d, ns where len(w) >= n
), dw as (
    select r, n, i, array_to_string(w[i : i + n - 1], ' ') as win from ds
), h as (
    select dw.r, dw.i, dw.n, bw.item from dw join bw on dw.win = bw.win and dw.n = bw.n
), hw as (
    select r, count(distinct p) as n_hit from (select r, unnest(range(i, i + n)) as p from h) group by r
), hi as (
    select r, count(*) as n_items, string_agg(item, ',' order by item) as items from (select distinct r, item from h) group by r
)
select doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
    sha256(coalesce(items, '')) as items_sha256, n_hit is not null as contaminated
from d left join hw using (r) left join hi using (r)
"""
