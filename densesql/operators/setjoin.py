"""Set-similarity joins that never compare all pairs.

The exact join orders each set's members by rarity, keeps the prefix in which any
similar set must share a member, joins on that member under length and position
filters, and verifies.  The approximate one takes its candidates from MinHash bands.

Every row's items are hashed once and staged.  Equal sets are folded first and expanded
at the end, so that copies meet once.  Rarity comes from counts of members in hash
classes, a table of fixed size: any one order keeps the join exact, and no member is
shuffled for it.  A sketch, in which two sets differ in no more bits than in members,
drops most unlike pairs inside the join, before they are written; pairs of wide sets,
for which it is too short, are compared by bitmaps that grow with the sets.  What is
left is compared whole, in tiles: the sets of a group of similar ones are carried in
blocks, not once for each of their pairs.  Entries and carried sets go in passes of
bounded size, whose shuffles end one by one.
Defined results: null members do not count, and an empty set has no pair.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from hashlib import blake2b
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.plans.rowset import picked
from densesql.plans.staging import Staging

#: Hash classes of members whose counts give rarity.
CLASSES = 1 << 16
#: Longs of a set's sketch.
SKETCH = 8
#: Sets of more members also have a bitmap that grows with them, of so many bits a member at least, for the pairs that their sketches leave.
WIDE, A_MEMBER = 32 * SKETCH, 2
#: Prefix entries of one pass, and members of the sets that one pass compares.
ENTRIES, COMPARED = 8 << 20, 16 << 20
#: Members of a block of sets that are carried together.
BLOCK = 1 << 16
#: Members before an entry's own by which a pair is known to have met.
BEFORE = 2
#: Bytes of an Arrow batch on its way to Python.
BATCH_BYTES = 4 << 20
WORD = re.compile("[a-z0-9_]+")


def bounded_batches(spark: SparkSession) -> None:
    """Bound the bytes of an Arrow batch (a runtime setting)."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if int(spark.conf.get(key).rstrip("b")) > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def word_sets(df: DataFrame, key: str, text: str, name: str) -> DataFrame:
    """(key, name): the distinct tokens of each text, as ``text.tokens`` has them, whose regular expression takes ten times as long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [list(dict.fromkeys(WORD.findall((x or "").lower()))) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.list_(pa.string()))], names=[key, name])

    bounded_batches(df.sparkSession)
    return df.select(key, text).mapInArrow(run, f"{key} {df.schema[key].dataType.simpleString()}, {name} array<string>")


def _levels(sets: DataFrame) -> bytes:
    """One byte for each hash class of members: higher for commoner ones."""
    found = sets.select(F.explode_outer("members").alias("h")).groupBy(F.pmod("h", F.lit(CLASSES)).alias("c")).count()  # outer: no filter that hashes anew
    out = bytearray(CLASSES)
    for c, n in found.where("c is not null").collect():  # as many rows as there are hash classes
        out[c] = min(255, 4 * n.bit_length() + (n >> max(0, n.bit_length() - 3) & 3))
    return bytes(out)


def _lists(column: pa.Array) -> Iterator[np.ndarray]:
    """Each row's list as an array of signed longs."""
    flat, ends = column.values.to_numpy(), column.offsets.to_numpy()
    yield from (flat[i:j] for i, j in zip(ends[:-1], ends[1:], strict=True))


def _listed(rows: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(x) for x in rows])]).astype(np.int32)
    return pa.ListArray.from_arrays(ends, np.concatenate(rows) if rows else np.empty(0, dtype=np.int64))


def _parities(members: np.ndarray, size: int) -> np.ndarray:
    """Of each of ``size`` bits the parity of the members that fall on it: two sets differ in no more bits than in members."""
    return np.packbits(np.bincount(members & size - 1, minlength=size).astype(np.uint8) & 1).view(np.int64)


def _marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of each key and its members' hashes: these in order, their number, two hashes of the whole set, its bitmap after that number, and its sketch."""
    for batch in batches:
        own = [np.unique(x) for x in _lists(batch.column(1))]
        same = np.frombuffer(b"".join(blake2b(x.tobytes(), digest_size=16).digest() for x in own), dtype=np.int64)
        marks = np.array([_parities(x, 64 * SKETCH) for x in own], dtype=np.int64).reshape(-1, SKETCH)
        bits = [np.concatenate([[len(x)], _parities(x, 1 << (A_MEMBER * len(x) - 1).bit_length())]) if len(x) > WIDE else x[:0] for x in own]
        n = pa.array([len(x) for x in own], pa.int32())
        columns = {"member": batch.column(0), "members": _listed(own), "n": n, "a": same[::2], "b": same[1::2], "bits": _listed(bits)}
        yield pa.RecordBatch.from_pydict(columns | {f"s{k}": marks[:, k] for k in range(SKETCH)})


def _folded(df: DataFrame, key: str, items: str, staging: Staging) -> tuple[DataFrame, DataFrame]:
    """(row_id, n, members, bits, s0, s1, ...) of one row for each set that is not empty, and (member, rep): every row's key and its set's row."""
    hashed = df.select(F.col(key).alias("member"), F.coalesce(F.transform(F.array_compact(items), lambda w: F.xxhash64(w)), F.array().cast("array<long>")).alias("h"))
    marks = "".join(f", s{k} long" for k in range(SKETCH))
    bounded_batches(df.sparkSession)
    sets = hashed.mapInArrow(_marked, f"member {df.schema[key].dataType.simpleString()}, members array<long>, n int, a long, b long, bits array<long>{marks}")
    staged = staging.table(sets, "sets", row_id="row_id").where("n > 0")
    reps = staged.groupBy("a", "b").agg(F.min("row_id").alias("rep"))
    classes = staging.table(staged.select("member", "a", "b").join(reps, ["a", "b"]).select("member", "rep"), "classes")
    return picked(staged.drop("member", "a", "b"), classes.select(F.col("rep").alias("row_id")), "row_id"), classes


def _likely(entries: DataFrame, on: list[str], t: float, fits: Column) -> DataFrame:
    """(u, v, wide): rows that meet in an entry and may be similar by their sizes, sketches and ``fits``; u has fewer members, or is the earlier row of as many.

    Of a ``wide`` pair both sets have bitmaps.
    """
    names = [c for c in entries.columns if c not in on]
    a, b = (entries.select(*on, *[F.col(c).alias(f"{side}{c}") for c in names]) for side in ("u_", "v_"))
    if "few" in names:
        a = a.where("u_few")
    apart = sum((F.bit_count(F.col(f"u_s{k}").bitwiseXOR(F.col(f"v_s{k}"))) for k in range(SKETCH)), F.lit(0))
    ordered = (F.col("u_n") < F.col("v_n")) | ((F.col("u_n") == F.col("v_n")) & (F.col("u_row_id") < F.col("v_row_id")))
    near = (F.col("u_n") >= F.col("v_n") * t - 1e-9) & (apart <= (F.col("u_n") + F.col("v_n")) * ((1 - t) / (1 + t)) + 1e-9)
    met = a.join(b.hint("merge"), on).where(ordered & near & fits)
    return met.select(F.col("u_row_id").alias("u"), F.col("v_row_id").alias("v"), (F.col("u_n") > WIDE).alias("wide")).distinct()


def _pairs(entries: DataFrame, count: int, on: list[str], sets: DataFrame, classes: DataFrame, t: float, staging: Staging, fits: Column) -> DataFrame:
    """(left_id, right_id, overlap) of the pairs that meet and reach ``t``, and of all equal ones."""
    passes = max(1, -(-count // ENTRIES))
    found = None
    for k in range(passes):
        part = staging.table(_likely(entries.where(F.pmod(F.xxhash64(*on), F.lit(passes)) == k), on, t, fits), f"likely-{k}")
        found = part if found is None else found.union(part)
    likely = staging.table(found.distinct(), "likely") if passes > 1 else found
    alike = _by_tiles(likely.where("wide"), sets.select("row_id", F.col("bits").alias("x")), lambda us, vs, own: _close(us, vs, own, t), staging, "close")
    rest = staging.table(alike.select("u", "v").union(likely.where("not wide").select("u", "v")), "rest")
    scored = _by_tiles(rest, sets.select("row_id", F.col("members").alias("x")), lambda us, vs, own: _shared(us, vs, own, t), staging, "scored")
    left, right = (classes.select(F.col("member").alias(f"{x}_id"), F.col("rep").alias(x)) for x in "uv")
    unlike = scored.join(left, "u").join(right, "v").select("u_id", "v_id", "overlap")
    equal = left.join(right, F.col("u") == F.col("v")).where("u_id < v_id").select("u_id", "v_id", F.lit(1.0).alias("overlap"))
    return unlike.union(equal).select(F.least("u_id", "v_id").alias("left_id"), F.greatest("u_id", "v_id").alias("right_id"), "overlap")


def _tiled(pairs: DataFrame, sizes: DataFrame, staging: Staging, name: str) -> tuple[DataFrame, DataFrame]:
    """(u, v, gu, gv): the pairs with their sets' blocks, and (row_id, n, gu, gv): each set once for every two blocks that compare it.

    Sets with the same smallest neighbour, as those of one group of similar sets have, lie
    in blocks of some BLOCK longs: however many pairs a group has, it is carried once a block.
    """
    both = lambda *of: F.explode(F.array(*[F.struct(F.col(x).alias("row_id"), F.col(y).alias(of[2])) for x, y in of[:2]])).alias("e")
    ends = pairs.select(both(("u", "v"), ("v", "u"), "o")).select("e.*")
    labels = ends.groupBy("row_id").agg(F.least("row_id", F.min("o")).alias("label")).join(sizes, "row_id")
    near = staging.table(labels, f"{name}-labels")
    blocks = near.groupBy("label").agg(F.ceil(F.sum("n") / BLOCK).alias("blocks"))
    homes = staging.table(near.join(blocks, "label").select("row_id", "n", F.xxhash64("label", F.pmod(F.xxhash64("row_id"), F.col("blocks"))).alias("g")), f"{name}-homes")
    at = [homes.select(F.col("row_id").alias(x), F.col("n").alias(f"n{x}"), F.col("g").alias(f"g{x}")) for x in "uv"]
    placed = staging.table(pairs.select("u", "v").join(at[0], "u").join(at[1], "v"), f"{name}-placed")
    each = placed.select("gu", "gv", both(("u", "nu"), ("v", "nv"), "n")).select("gu", "gv", "e.*")
    return placed.select("u", "v", "gu", "gv"), staging.table(each.distinct(), f"{name}-carried")


def _close(us: np.ndarray, vs: np.ndarray, own: list[np.ndarray], t: float) -> Iterator[tuple[int, float]]:
    """The place and a likelihood of each pair whose bitmaps, after the number of members, differ in no more bits than similar sets differ in members."""
    for k, (u, v) in enumerate(zip(us.tolist(), vs.tolist(), strict=True)):
        a, b = own[u], own[v]
        n, a, b = int(a[0] + b[0]), a[1:], b[1:]
        a, b = (x.reshape(-1, min(len(a), len(b))) for x in (a, b))  # a longer one is laid over itself
        apart = int(np.bitwise_count((np.bitwise_xor.reduce(a) ^ np.bitwise_xor.reduce(b)).view(np.uint64)).sum())  # of signed longs it would count the absolute value's bits
        if apart <= n * ((1 - t) / (1 + t)) + 1e-9:
            yield k, 1 - apart / n


def _shared(us: np.ndarray, vs: np.ndarray, own: list[np.ndarray], t: float) -> Iterator[tuple[int, float]]:
    """The place and overlap of each similar pair."""
    words, at = np.unique(np.concatenate(own), return_inverse=True)
    own = np.split(at, np.cumsum([len(x) for x in own])[:-1])
    mark, before = np.zeros(len(words), dtype=bool), -1
    for k in np.argsort(us, kind="stable").tolist():
        u, v = int(us[k]), int(vs[k])
        if u != before:
            mark[:] = False
            mark[own[u]] = True
            before = u
        same = int(np.count_nonzero(mark[own[v]]))
        overlap = same / (len(own[u]) + len(own[v]) - same)
        if overlap >= t - 1e-9:
            yield k, overlap


def _compared(batches: Iterator[pa.RecordBatch], compare: Callable) -> Iterator[pa.RecordBatch]:
    """(u, v, overlap) of what ``compare`` finds among each tile's pairs, given as places in its list of sets."""
    for batch in batches:
        out = []
        for n in range(batch.num_rows):
            us, vs, ids = (batch.column(k).slice(n, 1).flatten().to_numpy() for k in range(3))
            order = np.argsort(ids)
            places = (order[np.searchsorted(ids, x, sorter=order)] for x in (us, vs))
            found = list(compare(*places, list(_lists(batch.column(3).slice(n, 1).flatten()))))
            if found:
                at, overlap = (np.array(x) for x in zip(*found, strict=True))
                out.append((us[at], vs[at], overlap.astype(float)))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*out, strict=True)], names=["u", "v", "overlap"])


def _by_tiles(pairs: DataFrame, rows: DataFrame, compare: Callable, staging: Staging, name: str) -> DataFrame:
    """(u, v, overlap) of the pairs that ``compare`` finds similar by their rows' ``x``."""
    placed, carried = _tiled(pairs, rows.select("row_id", F.size("x").alias("n")), staging, name)
    passes = max(1, -(-(carried.agg(F.sum("n")).first()[0] or 0) // COMPARED))
    bounded_batches(pairs.sparkSession)
    found = None
    for k in range(passes):
        asked, each = (x.where(F.pmod(F.xxhash64("gu", "gv"), F.lit(passes)) == k) for x in (placed, carried))
        lists = each.select("gu", "gv", "row_id").join(rows, "row_id").groupBy("gu", "gv").agg(F.collect_list(F.struct("row_id", "x")).alias("own"))
        tiles = asked.groupBy("gu", "gv").agg(F.collect_list(F.struct("u", "v")).alias("asked")).join(lists, ["gu", "gv"])
        given = tiles.select(F.col("asked.u").alias("us"), F.col("asked.v").alias("vs"), F.col("own.row_id").alias("ids"), F.col("own.x").alias("x"))
        part = staging.table(given.mapInArrow(lambda x: _compared(x, compare), "u long, v long, overlap double"), f"{name}-{k}")
        found = part if found is None else found.union(part)
    return found


def _fronts(batches: Iterator[pa.RecordBatch], table: np.ndarray, t: float) -> Iterator[pa.RecordBatch]:
    """The members in which a similar set must share one, rarest first, instead of all members."""
    for batch in batches:
        out = []
        for x in _lists(batch.column(batch.num_columns - 1)):
            order = np.lexsort((x, table[x & CLASSES - 1]))
            out.append(x[order[: len(x) - ceil(len(x) * t - 1e-9) + 1]])
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], _listed(out)], names=[*batch.schema.names[:-1], "front"])


def prefix_join(df: DataFrame, key: str, items: str, t: float) -> DataFrame:
    """(left_id, right_id, overlap) for all pairs of different keys with overlap of at least ``t``, left before right.

    Of two sets the smaller needs to meet in fewer members (``few``), as the larger has as many at least.
    A pair that shares one of the members just before (``p0``, ``p1``) has met there already.
    """
    staging = Staging(df.sparkSession, "prefix-join")
    sets, classes = _folded(df, key, items, staging)
    table = np.frombuffer(_levels(sets), dtype=np.uint8)
    marks = [f"s{k}" for k in range(SKETCH)]
    schema = "row_id long, n int" + "".join(f", {s} long" for s in marks)
    bounded_batches(df.sparkSession)
    fronts = sets.select("row_id", "n", *marks, "members").mapInArrow(lambda x: _fronts(x, table, t), f"{schema}, front array<long>")
    fronts = staging.table(fronts, "fronts")
    both = 2 * t / (1 + t)
    short = F.col("n") - F.ceil(F.col("n") * both - 1e-9).cast("int") + 1
    before = [F.when(F.col("i") > k, F.get("front", F.col("i") - k - 1)).alias(f"p{k}") for k in range(BEFORE)]
    entries = fronts.select("row_id", "n", *marks, "front", F.posexplode("front").alias("i", "w")).select("row_id", "n", *marks, "i", "w", *before, (F.col("i") < short).alias("few"))
    least = F.ceil((F.col("u_n") + F.col("v_n")) * (t / (1 + t)) - 1e-9)
    room = F.least(F.col("u_n") - F.col("u_i"), F.col("v_n") - F.col("v_i"))
    again = F.lit(False)
    for j in range(BEFORE):
        for k in range(BEFORE):
            again = again | (F.col(f"u_p{j}") == F.col(f"v_p{k}"))
    fits = (room >= least) & ~F.coalesce(again, F.lit(False))
    return _pairs(entries, fronts.agg(F.sum(F.size("front"))).first()[0] or 0, ["w"], sets, classes, t, staging, fits)


def minhash_join(df: DataFrame, key: str, items: str, t: float, bands: int = 16, rows: int = 4) -> DataFrame:
    """As ``prefix_join``, over pairs that agree in some band of MinHash values."""
    staging = Staging(df.sparkSession, "minhash-join")
    sets, classes = _folded(df, key, items, staging)
    low = lambda s: F.array_min(F.transform("members", lambda h: F.xxhash64(F.lit(s), h)))
    keys = F.array(*[F.struct(F.lit(b).alias("band"), F.xxhash64(*[low(b * rows + r) for r in range(rows)]).alias("h")) for b in range(bands)])
    marks = [f"s{k}" for k in range(SKETCH)]
    banded = staging.table(sets.select("row_id", "n", *marks, keys.alias("keys")), "banded")
    return _pairs(banded.select("row_id", "n", *marks, F.inline("keys")), banded.count() * bands, ["band", "h"], sets, classes, t, staging, F.lit(True))
