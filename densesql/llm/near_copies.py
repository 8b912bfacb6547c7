"""Near-duplicates of 5-word shingles: SimHash with covering tables, then an exact set-similarity join.

A text is the set of its 5-word shingles, as 64-bit hashes; two texts are near copies
where the Jaccard similarity of their sets is at least 0.8, and groups are the connected
components of that relation.  The covering tables of the SimHash operator first link the
closest copies, each link verified on whole sets.  Fingerprints of near copies of 0.8 may
differ in some ten of 64 bits, beyond any radius that covering tables can afford, so an
exact join finds the rest.  Shingles have one order, rarer hash classes first; similar
sets share one among the first fifth of each (the prefix), so prefixes are joined by
shingle under length and position filters and what is left is verified on whole sets.

Equal sets count once from the start.  Groups under a shingle are not expanded at first:
in a round each set meets only the next one of its group in a shuffled order, which
joins most of a large group of near copies, and rounds go on while they do.  At the end
every pair that shares a prefix shingle and is still in different components is compared,
so none is missed.  A short sketch in each entry drops most pairs of unlike sets inside
that join, before they are written.

Texts are not shuffled: rows are picked from the staged table by bitmaps of their ids.

Defined results: a text of fewer words than a shingle is one shingle, a null or blank one
has the empty set, and both are near copies of equal sets only; null doc_ids come last;
repeated rows are equal sets; an empty table gives no rows; other columns go along.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from densesql.llm.common import bounded, map_rows, numbered, small_batches, trimmed
from densesql.llm.op2_simhash import links, majority, shingle_hashes, signed
from densesql.plans.components import connected_components
from densesql.plans.rowset import picked
from densesql.plans.staging import Staging

SEED, SHINGLE = 42, 5
#: Similarity of at least this many fifths.
FIFTHS = 4
#: Hash classes of shingles whose counts give rarity.
CLASSES = 1 << 16
#: Least bits of a set's bitmap, and bits for each member, rounded up to a power of two: two bitmaps of one length differ in no more bits than their sets in members.
BITMAP, A_MEMBER = 2048, 2
#: Shingles of candidate pairs that are compared in one pass; more of them go in PASSES passes, whose shuffles end one by one.
ONE_PASS, PASSES = 8 << 20, 8
#: Up to so many pairs their rows are picked by a broadcast bitmap of row ids, about a bit a row; beyond that ids are joined.
FEW_PAIRS = 1 << 26
#: Most rounds in which a set meets one other per shingle, after the round of fingerprints.
ROUNDS = 6
#: Another round follows one that left at most this share of the pairs still apart, if these are more than the entries.
WORTH = 0.8
#: At the end of two components so many pairs are compared first, then as many again, then all that are left if they are still apart.
WAVES = (1, 8, None)
#: In the rounds before, each set's likeliest pair is compared first, then those left of sets still apart.
NEAREST = ("nearest", None)
#: Longs of an entry's sketch, in which two sets differ in no more bits than in members.
SKETCH = 4


def shingles(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """The distinct shingles of a text as ordered unsigned hashes."""
    return np.unique(shingle_hashes(text, size).astype(np.uint64))


def _levels(docs: DataFrame, size: int) -> bytes:
    """One byte for each hash class of shingles: higher for commoner ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(CLASSES, dtype=np.int64)
        for batch in batches:
            for piece in bounded(batch):
                for text in piece.column(0).to_pylist():
                    np.add.at(seen, (shingles(text, size) % CLASSES).astype(np.int64), 1)
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(seen[at])], names=["c", "n"])

    small_batches(docs.sparkSession)
    counts = docs.select("text").mapInArrow(trimmed(run), "c long, n long").groupBy("c").agg(F.sum("n").alias("n"))
    out = bytearray(b"\x01" * CLASSES)
    for c, n in counts.collect():  # as many rows as there are hash classes
        out[c] = min(255, 1 + 4 * n.bit_length() + (n >> max(0, n.bit_length() - 3) & 3))
    return bytes(out)


def _least(n: Column, m: Column) -> Column:
    """The least overlap of two similar sets of these sizes."""
    return F.ceil((n + m) * FIFTHS / (FIFTHS + 5))


def _fits(other: str) -> Column:
    """Whether two prefix entries, the second with a prefix to its names, may belong to similar sets."""
    n, m = F.col("n"), F.col(f"{other}n")
    room = F.least(n - F.col("i"), m - F.col(f"{other}i"))
    apart = sum((F.bit_count(F.col(f"s{k}").bitwiseXOR(F.col(f"{other}s{k}"))) for k in range(SKETCH)), F.lit(0))
    return (5 * F.least(n, m) >= FIFTHS * F.greatest(n, m)) & (room >= _least(n, m)) & (apart <= n + m - 2 * _least(n, m))


def bitmap(hashes: np.ndarray) -> list[int]:
    """The parities of a set's members by hash class, as signed longs; classes grow with the set, so that unlike long sets differ in enough of them."""
    size = max(BITMAP, 1 << max(0, A_MEMBER * len(hashes) - 1).bit_length())
    odd = np.bincount((hashes % np.uint64(size)).astype(np.int64), minlength=size).astype(np.uint8) & 1
    return np.packbits(odd).view(np.int64).tolist()


def _likely(pairs: DataFrame, distinct: DataFrame) -> DataFrame:
    """(u, v, apart): the pairs whose bitmaps differ in no more bits than similar sets differ in members.

    Similar sets have bitmaps of one length or of twice the other's, whose halves are then laid over each other.
    """
    marks = [distinct.select(F.col("sid").alias(x), F.col("n").alias(f"n{x}"), F.col("bits").alias(f"b{x}")) for x in "uv"]
    both = pairs.join(marks[0], "u").join(marks[1], "v")

    def halved(long: str, short: str) -> Column:
        half = F.expr(f"cast(size({long}) div 2 as int)")
        over = F.zip_with(F.slice(long, F.lit(1), half), F.slice(long, half + 1, half), lambda a, b: a.bitwiseXOR(b))
        return F.when(F.size(long) > F.size(short), over).otherwise(F.col(long))

    differ = F.zip_with(halved("bu", "bv"), halved("bv", "bu"), lambda a, b: F.bit_count(F.coalesce(a, F.lit(0).cast("long")).bitwiseXOR(F.coalesce(b, F.lit(0).cast("long")))))
    apart = F.aggregate(differ, F.lit(0), lambda n, x: n + x)
    close = both.select("u", "v", "nu", "nv", F.explode(F.array(apart)).alias("apart"))
    return close.where(F.col("apart") <= F.col("nu") + F.col("nv") - 2 * _least(F.col("nu"), F.col("nv"))).select("u", "v", "apart")


def _verify(pairs: DataFrame, texts: DataFrame, size: int, few: bool) -> DataFrame:
    """(u, v): the pairs whose sets are similar indeed; ``texts`` has (row_id, text), a set's id being one of its rows'.

    Where the pairs are ``few`` a bitmap of their rows goes to the texts, which then are not shuffled.
    """
    ids = pairs.select(F.explode(F.array("u", "v")).alias("row_id"))
    wanted = picked(texts, ids, "row_id") if few else texts.join(ids.distinct(), "row_id", "left_semi")

    def make() -> Callable:
        return lambda sids, given: [(s, shingles(t, size).view(np.int64).tolist()) for s, t in zip(sids, given, strict=True)]

    sets = map_rows(wanted, ["row_id", "text"], "sid long, m array<long>", make)
    left, right = (sets.select(F.col("sid").alias(x), F.col("m").alias(f"m{x}")) for x in "uv")
    both = pairs.join(left, "u").join(right, "v").withColumn("same", F.size(F.array_intersect("mu", "mv")))
    return both.where(5 * F.col("same") >= FIFTHS * (F.size("mu") + F.size("mv") - F.col("same"))).select("u", "v")


def _verified(pairs: DataFrame, distinct: DataFrame, texts: DataFrame, size: int, staging: Staging, name: str) -> DataFrame:
    """``_verify`` of staged pairs, staged; the number of passes changes what is on disk at once and nothing else."""
    count, carried = pairs.join(distinct.select(F.col("sid").alias("u"), "n"), "u").agg(F.count("n"), F.sum("n")).first()
    passes = PASSES if (carried or 0) > ONE_PASS else 1
    found = None
    for k in range(passes):
        part = pairs.select("u", "v").where(F.pmod(F.xxhash64("u"), F.lit(passes)) == k)
        new = staging.table(_verify(part, texts, size, count <= FEW_PAIRS), f"{name}-{k}")
        found = new if found is None else found.union(new)
    return found


def _close_pairs(distinct: DataFrame, staging: Staging) -> DataFrame:
    """(u, v): sets of equal fingerprints, and one set each of fingerprints that the covering tables link."""
    by_fp = staging.table(distinct.groupBy("fp").agg(F.min("sid").alias("low")), "prints")
    equal = distinct.join(by_fp, "fp").where("sid != low").select("sid", "low")
    ends = [by_fp.select(F.col("fp").alias(x), F.col("low").alias(f"{x}_low")) for x in "uv"]
    linked = links(by_fp, "fp").join(ends[0], "u").join(ends[1], "v").select(F.col("u_low").alias("sid"), F.col("v_low").alias("low"))
    both = equal.union(linked)
    return both.select(F.least("sid", "low").alias("u"), F.greatest("sid", "low").alias("v")).distinct()


def _between(pairs: DataFrame, roots: DataFrame) -> DataFrame:
    """(u, v, lo, hi): the pairs of different components, with these in order."""
    ends = [roots.select(F.col("node").alias(x), F.col("root").alias(f"r{x}")) for x in "uv"]
    both = pairs.join(ends[0], "u", "left").join(ends[1], "v", "left").select("u", "v", F.coalesce("ru", "u").alias("ru"), F.coalesce("rv", "v").alias("rv"))
    return both.where("ru != rv").select("u", "v", F.least("ru", "rv").alias("lo"), F.greatest("ru", "rv").alias("hi"))


def _wave(pairs: DataFrame, roots: DataFrame, most: int, staging: Staging, name: str) -> tuple[DataFrame, DataFrame]:
    """Up to ``most`` pairs of every two components, and all other pairs."""
    order = Window.partitionBy("lo", "hi").orderBy(F.xxhash64("u", "v"))
    ranked = staging.table(_between(pairs, roots).select("u", "v", F.row_number().over(order).alias("k")), name)
    return ranked.where(F.col("k") <= most).select("u", "v"), ranked.where(F.col("k") > most).select("u", "v")


def _nearest(pairs: DataFrame, staging: Staging, name: str) -> tuple[DataFrame, DataFrame]:
    """Of each set the pair whose bitmaps differ least, and all other pairs."""
    ends = pairs.select(F.explode(F.array("u", "v")).alias("node"), F.struct("apart", F.xxhash64("u", "v").alias("h"), "u", "v").alias("p"))
    first = staging.table(ends.groupBy("node").agg(F.min("p").alias("p")).select("p.u", "p.v").distinct(), name)
    return first, pairs.join(first, ["u", "v"], "left_anti").select("u", "v")


def _apart(left: DataFrame) -> tuple[int, float]:
    """Entries, and pairs of entries under the same shingle in different components."""
    counts = left.groupBy("w", "root").agg(F.count(F.lit(1)).alias("c")).groupBy("w").agg(F.sum("c").alias("n"), F.sum(F.col("c").cast("double") * F.col("c")).alias("q"))
    n, pairs = counts.agg(F.sum("n"), F.sum(F.col("n").cast("double") * F.col("n") - F.col("q"))).first()
    return n or 0, (pairs or 0.0) / 2


def similar_sets(printed: DataFrame, staging: Staging, size: int, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """(sid, first) of every distinct set, and (node, root) of those with a near copy; a set's id is its first row's.

    ``printed`` has (row_id, doc_id, text, sid, fp, n, prefix, bits, s0, s1, ...).
    """
    marks = [f"s{k}" for k in range(SKETCH)]
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row_id")).alias("first")
    whole = [F.first(c).alias(c) for c in ("fp", "n", "prefix", "bits", *marks)]  # equal sets may differ in repeats, so in fp: any one will do
    folded = printed.groupBy("sid").agg(first, *whole)
    distinct = staging.table(folded.withColumn("sid", F.col("first.row_id")), "distinct")
    entries = distinct.select("sid", "n", *marks, F.posexplode("prefix").alias("i", "w"))
    company = entries.withColumn("size", F.count(F.lit(1)).over(Window.partitionBy("w"))).where("size > 1").drop("size")
    shared = staging.table(company, "shared")
    near = staging.table(_close_pairs(distinct.where("n > 0"), staging), "near")
    close = staging.table(_likely(near, distinct), "close")
    texts = printed.select("row_id", "text")
    found = _verified(close, distinct, texts, size, staging, "similar")
    roots = connected_components(found, Staging(printed.sparkSession, "copies"))
    names, before, name = ["sid", "n", "i", *marks, "root"], None, "shared"
    for k in range(rounds + 1):
        rooted = shared.drop("root").join(roots, shared["sid"] == roots["node"], "left").select("w", *names[:-1], F.coalesce("root", "sid").alias("root"))
        whole_group = Window.partitionBy("w")
        mixed = rooted.withColumns({"lo": F.min("root").over(whole_group), "hi": F.max("root").over(whole_group)}).where("lo != hi").drop("lo", "hi")
        shared = staging.table(mixed, f"left-{k}")
        staging.drop(name)
        name = f"left-{k}"
        n, apart = _apart(shared)
        last = k == rounds or apart <= n or (before is not None and apart > WORTH * before)
        before = apart
        if last:
            met = shared.join(shared.select("w", *[F.col(x).alias(f"e{x}") for x in names]), "w").where("root < eroot")
        else:
            order = Window.partitionBy("w").orderBy("n" if k % 2 else F.lit(0), F.xxhash64(F.lit(k), "w", "sid"))
            flat = shared.withColumn("e", F.lead(F.struct(*names)).over(order)).where("e is not null and e.root != root")
            met = flat.select("*", *[F.col("e")[x].alias(f"e{x}") for x in names])
        pairs = met.where(_fits("e")).select(F.least("sid", "esid").alias("u"), F.greatest("sid", "esid").alias("v"))
        pairs = staging.table(pairs.distinct(), f"met-{k}")
        likely = staging.table(_likely(pairs, distinct), f"pairs-{k}")
        staging.drop(f"met-{k}")
        for wave, most in enumerate(WAVES if last else NEAREST):
            if most is None:
                taken, rest = likely, None
            elif last:
                taken, rest = _wave(likely, roots, most, staging, f"wave-{wave}")
            else:
                taken, rest = _nearest(likely, staging, f"nearest-{k}")
            found = found.union(_verified(taken, distinct, texts, size, staging, f"similar-{k}-{wave}"))
            roots = connected_components(found, Staging(printed.sparkSession, f"copies-{k}-{wave}"))
            likely = rest if rest is None else staging.table(_between(rest, roots).select("u", "v"), f"rest-{k}-{wave}")
        if last:
            break
    staging.drop(name)
    return distinct.select("sid", "first"), roots


def keep_one(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """The first row of every group of near copies, by doc_id (nulls last), with the columns of ``docs``."""
    staging = Staging(docs.sparkSession, "copies")
    own, names = numbered(docs, "doc_id", "text")
    levels = _levels(own, size)

    def make() -> Callable:
        table = np.frombuffer(levels, dtype=np.uint8)

        def one(text: str | None) -> tuple:
            hashes = shingle_hashes(text, size)
            own = np.unique(hashes.astype(np.uint64))
            n = len(own)
            order = np.lexsort((own, table[(own % CLASSES).astype(np.int64)]))[: n + FIFTHS * -n // 5 + 1 if n else 0]
            sid = xxh64_intdigest(own.tobytes(), SEED)
            folded = np.bincount((own % np.uint64(64 * SKETCH)).astype(np.int64), minlength=64 * SKETCH).astype(np.uint8) & 1
            return signed(sid), signed(majority(hashes)), n, own[order].view(np.int64).tolist(), bitmap(own), *np.packbits(folded).view(np.int64).tolist()

        return lambda ids, texts: [(i, *one(t)) for i, t in zip(ids, texts, strict=True)]

    schema = "doc_id long, sid long, fp long, n int, prefix array<long>, bits array<long>" + "".join(f", s{k} long" for k in range(SKETCH))
    printed = staging.table(map_rows(own, ["doc_id", "text"], schema, make, tuple(names)), "printed", row_id="row_id")
    text = printed.withColumn("text", F.col(f"k{docs.columns.index('text')}"))
    distinct, roots = similar_sets(text, staging, size)
    rooted = distinct.join(roots, distinct["sid"] == roots["node"], "left").withColumn("group", F.coalesce("root", "sid"))
    stays = staging.table(rooted.groupBy("group").agg(F.min("first").alias("first")).select("first.row_id"), "stays")
    staging.drop("distinct")
    return picked(printed, stays, "row_id").select(*[f"k{n}" for n in range(len(names))]).toDF(*docs.columns)
