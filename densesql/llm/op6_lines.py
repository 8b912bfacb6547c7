"""Line dedup by an exact set-similarity join.

A line is the set of its words.  Words are ordered by rarity, the commonest last.  The
first word that two sets with Jaccard similarity of at least 0.8 have in common lies among
the first few of each, and the second at most one place further.  A rarer word is a key of
its own; common words are keys in pairs, so that no key gathers all lines with a frequent
word: if the first shared word is common, so is the second.  Lines of many words have their
common words as keys of their own instead, lines of middling size have both.
Sets of up to three words are similar to equal sets only and have one key, the set.

Lines are joined by key.  Lengths, positions and a sketch, in which two sets differ in
no more bits than in words, bound the overlap inside the join, before any pair is
written; what is left is verified on the words, of each line first the pair whose sketches
differ least, then the others of lines that stay open.
Rarity comes from counts of all words in hash classes, a table of fixed size:
any one order of words keeps the join exact, and a rarer word still comes earlier.

A line goes if an earlier one (by doc_id, then place in the table and the text) has the
same words in the same order, or is similar.  Equal lines are folded first.  Keys whose
counts may be large are not expanded at first: each of their lines first meets the earliest
line of its key, and only lines that stay open meet the others.  The largest are dealt over
several tasks, whose earliest lines then meet.

All of it is DataFrame functions.  Defined results: a null text has no lines; lines
without a word always stay and do not count; null doc_ids come last; repeated rows give
one result row each, the later losing its lines; other columns are ignored.  Where a
doc_id is null or repeated the rows are staged to fix their place in the table;
otherwise ``docs`` is read twice and must give the same rows both times.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.llm.common import documents, numbered, squeezed
from densesql.plans.staging import Staging

#: Hash classes of words whose counts give rarity.
CLASSES = 1 << 18
#: Similarity of at least this many fifths; sets of up to so many words match equal sets only.
FIFTHS, EQUAL_ONLY = 4, 3
#: From this level (counts of 1024 and more) words are common: keys in pairs, in lines of up to MOST_PAIRED words.
COMMON, MOST_PAIRED = 23, 75
#: Lines of more words have a sketch of 128 bits, others of 64.
WIDE = 48
#: A common key's group is dealt to tasks of about two to this power lines.
GROUP_BITS = 17

LINE, EARLY, ENTRY = ["d", "r", "l"], ["ed", "er", "el"], ["d", "r", "l", "n", "i", "s", "t"]
#: Bits of a word's key below its level.
KEY_BITS = 56


def _lines(rows: DataFrame) -> DataFrame:
    """(d, r, l, words): every line with a word, its place and its words with one blank between them."""
    each = rows.select("d", "r", F.posexplode(F.split("text", "\n")).alias("l", "line")).where(F.col("line").rlike(r"[^\x20\x09-\x0D]"))
    line = F.col("line")
    odd = line.startswith(" ") | line.endswith(" ")
    for piece in ("  ", "\t", "\v", "\f", "\r"):
        odd = odd | line.contains(piece)
    return each.select(*LINE, F.when(odd, squeezed(line)).otherwise(line).alias("words"))


def _distinct(lines: DataFrame) -> DataFrame:
    """(d, r, l, words) of the first of equal lines."""
    keyed = lines.select(F.struct(*LINE).alias("p"), F.xxhash64(F.lit(1), "words").alias("a"), F.xxhash64(F.lit(2), "words").alias("b"), "words")
    return keyed.groupBy("a", "b").agg(F.min("p").alias("p"), F.first("words").alias("words")).select("p.*", "words")


def _levels(lines: DataFrame) -> list[int]:
    """A number from 1 to 126 for each hash class of words: twice the bits of its count, and the bit below the highest."""
    found = lines.select(F.explode(F.split("words", " ")).alias("w")).groupBy(F.xxhash64("w").bitwiseAND(F.lit(CLASSES - 1)).alias("c")).count()
    out = [1] * CLASSES
    for c, n in found.collect():  # as many rows as there are hash classes
        out[c] = min(126, 1 + 2 * n.bit_length() + (n >> max(0, n.bit_length() - 2) & 1))
    return out


def _members(words: Column, levels: list[int]) -> Column:
    """The distinct words as ordered numbers, rarest first: 7 bits of level above 56 bits of hash."""
    table = F.split(F.lit(",".join(map(str, levels))), ",").cast("array<long>")  # folded to a constant by the optimizer
    low = F.lit((1 << KEY_BITS) - 1)

    def key(h: Column) -> Column:
        return F.shiftleft(F.get(table, h.bitwiseAND(F.lit(CLASSES - 1)).cast("int")), KEY_BITS).bitwiseOR(h.bitwiseAND(low))

    return F.sort_array(F.transform(F.array_distinct(F.transform(F.split(words, " "), lambda x: F.xxhash64(x))), key))


def _meets() -> Column:
    """Whether two entries of a key, the earlier with names in e, may be those of the first words that similar lines share."""
    earlier = (F.col("ed") < F.col("d")) | ((F.col("ed") == F.col("d")) & ((F.col("er") < F.col("r")) | ((F.col("er") == F.col("r")) & (F.col("el") < F.col("l")))))
    s, t = (F.col(x).bitwiseXOR(F.col(f"e{x}")) for x in "st")
    most = (5 - FIFTHS) * (F.col("n") + F.col("en"))
    wide = F.when((F.col("n") > WIDE) & (F.col("en") > WIDE), (FIFTHS + 5) * (F.bit_count(s.bitwiseXOR(t)) + F.bit_count(t)) <= most).otherwise(True)
    apart = ((FIFTHS + 5) * F.bit_count(s) <= most) & wide
    sizes = (5 * F.col("n") >= FIFTHS * F.col("en")) & (5 * F.col("en") >= FIFTHS * F.col("n"))
    room = F.least(F.col("n") - F.col("i"), F.col("en") - F.col("ei"))
    return earlier & apart & sizes & ((FIFTHS + 5) * room >= FIFTHS * (F.col("n") + F.col("en")))


def _differ() -> Column:
    """Bits in which the sketches of two entries differ, those of 128 bits if both have one."""
    s, t = (F.col(x).bitwiseXOR(F.col(f"e{x}")) for x in "st")
    return F.when((F.col("n") > WIDE) & (F.col("en") > WIDE), F.bit_count(s.bitwiseXOR(t)) + F.bit_count(t)).otherwise(F.bit_count(s)).alias("differ")


def _keyed(lines: DataFrame, levels: list[int]) -> DataFrame:
    """(d, r, l, n, s, t, keys): each line's size, sketch (all folded, and the upper half) and keys (w, i), i the place of the key's first word."""
    sets = lines.select(*LINE, _members(F.col("words"), levels).alias("m")).withColumn("n", F.size("m"))
    low, common = F.lit((1 << KEY_BITS) - 1), F.lit(COMMON << KEY_BITS)

    def sketch(members: Column) -> Column:
        return F.aggregate(members, F.lit(0).cast("long"), lambda s, x: s.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), x.bitwiseAND(F.lit(63)).cast("int"))))

    high = F.when(F.col("n") > WIDE, sketch(F.filter("m", lambda x: x.bitwiseAND(F.lit(64)) != 0))).otherwise(F.lit(0).cast("long"))

    def joint(first: Column, all_of: Column) -> Column:
        return first.bitwiseAND(F.bitwise_not(low)).bitwiseOR(all_of.bitwiseAND(low))

    def entry(w: Column, i: Column) -> Column:
        return F.struct(w.alias("w"), i.cast("int").alias("i"))

    short = F.expr(f"cast(n - ({FIFTHS} * n + 4) div 5 + 1 as int)")
    places = F.transform(F.slice("m", 1, short + 1), entry)
    ones = F.filter(F.slice(places, 1, short), lambda e: (e["w"] < common) | (F.col("n") > MOST_PAIRED * FIFTHS // 5))
    often = F.filter(places, lambda e: e["w"] >= common)
    twos = F.flatten(F.transform(often, lambda a: F.transform(F.filter(often, lambda b: b["i"] > a["i"]), lambda b: entry(joint(a["w"], F.xxhash64(a["w"], b["w"])), a["i"]))))
    paired = (F.col("n") <= MOST_PAIRED) & (F.element_at("m", F.least("n", short + 1)) >= common)
    whole = F.array(entry(joint(F.element_at("m", 1), F.xxhash64("m")), F.lit(0)))
    keys = F.when(F.col("n") <= EQUAL_ONLY, whole).when(paired, F.concat(ones, twos)).otherwise(ones)
    return sets.select(*LINE, "n", sketch(F.col("m")).alias("s"), high.alias("t"), keys.alias("keys"))


def _entries(keyed: DataFrame, common: bool) -> DataFrame:
    """(w, d, r, l, n, i, s, t): the entries under common keys, or those under all others."""
    border = F.lit(COMMON << KEY_BITS)
    each = keyed.select(*LINE, "n", "s", "t", F.inline("keys"))
    return each.where(F.col("w") >= border if common else F.col("w") < border)


def _rare_pairs(keyed: DataFrame) -> DataFrame:
    """(ed, er, el, d, r, l, differ): lines that meet under a rarer key; both sides are one shuffle, as their plans are alike."""
    late, early = (_entries(keyed, False).select(F.col("w").alias(f"{side}w"), *[F.col(x).alias(f"{side}{x}") for x in ENTRY]) for side in ("a", "e"))
    met = late.join(early.hint("merge"), F.col("aw") == F.col("ew"))
    for x in ENTRY:
        met = met.withColumnRenamed(f"a{x}", x)
    return met.where(_meets()).select(*EARLY, *LINE, _differ())


def _grouped(entries: DataFrame) -> DataFrame:
    """Entries in company, with their part's earliest entry (ed, er, el, en, ei) and whether the word is dealt out."""
    bits = F.greatest(F.shiftright(F.shiftright("w", KEY_BITS) - 1, 1) - GROUP_BITS, F.lit(0))
    parts = F.call_function("shiftleft", F.lit(1).cast("long"), bits.cast("int"))
    dealt = entries.withColumns({"part": F.pmod(F.xxhash64(*LINE), parts), "dealt": bits > 0})
    part = Window.partitionBy("w", "part").orderBy(*LINE)
    size = F.count(F.lit(1)).over(part.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    grouped = dealt.withColumns({f"e{x}": F.first(x).over(part) for x in ENTRY} | {"size": size})
    return grouped.where("size > 1 or dealt").drop("part", "size")


def _first_pairs(shared: DataFrame) -> DataFrame:
    """(ed, er, el, d, r, l): lines and the earliest of their groups, where they may be similar."""
    tops = shared.where("dealt and ed = d and er = r and el = l")
    among = Window.partitionBy("w").orderBy(*LINE)
    tops = tops.withColumns({f"e{x}": F.first(x).over(among) for x in ENTRY})
    return shared.unionByName(tops).where(_meets()).select(*EARLY, *LINE).distinct()


def _rest_pairs(shared: DataFrame, gone: DataFrame) -> DataFrame:
    """The pairs of open lines and any earlier line of their groups."""
    late = shared.where("ed != d or er != r or el != l or dealt").select("w", *ENTRY).join(gone, LINE, "left_anti")
    early = shared.select("w", *[F.col(x).alias(f"e{x}") for x in ENTRY])
    return late.join(early, "w").where(_meets()).select(*EARLY, *LINE, _differ())


def _verify(pairs: DataFrame, lines: DataFrame, staging: Staging, name: str) -> DataFrame:
    """(d, r, l): the later lines of staged pairs that are similar indeed, word by word."""
    ends = pairs.select(F.explode(F.array(F.struct(*LINE), F.struct(*[F.col(f"e{x}").alias(x) for x in LINE]))).alias("p")).select("p.*").distinct()
    texts = staging.table(lines.join(ends, LINE, "left_semi"), f"{name}-texts")
    early = texts.select(*[F.col(x).alias(f"e{x}") for x in (*LINE, "words")])
    sets = F.array(F.struct(F.array_distinct(F.split("words", " ")).alias("m"), F.array_distinct(F.split("ewords", " ")).alias("em")))
    both = pairs.join(texts, LINE).join(early, EARLY).select(*LINE, F.inline(sets))
    same = both.select(*LINE, (F.size("m") + F.size("em")).alias("sizes"), F.explode(F.array(F.size(F.array_intersect("m", "em")))).alias("same"))
    return same.where(5 * F.col("same") >= FIFTHS * (F.col("sizes") - F.col("same"))).select(*LINE).distinct()


def _decide(rows: DataFrame, staging: Staging) -> DataFrame:
    """(d, r, n_first, n_similar, kept_lines) of every row with a line: firsts of equal lines, similar ones, those that stay."""
    lines = staging.table(_distinct(_lines(rows)), "distinct")
    keyed = staging.table(_keyed(lines, _levels(lines)), "keyed")
    shared = staging.table(_grouped(_entries(keyed, True)), "shared")
    near = staging.table(_first_pairs(shared), "near")
    gone = staging.table(_verify(near, lines, staging, "near"), "gone")
    met = staging.table(_rare_pairs(keyed), "met")
    staging.drop("keyed")
    rest = staging.table(met.join(gone, LINE, "left_anti").unionByName(_rest_pairs(shared, gone)).distinct(), "rest")
    staging.drop("shared")
    likeliest = rest.groupBy(*LINE).agg(F.min(F.struct("differ", *EARLY)).alias("e")).select(*[F.col("e")[x].alias(x) for x in EARLY], *LINE)
    likeliest = staging.table(likeliest, "likeliest")
    some = staging.table(_verify(likeliest, lines, staging, "likeliest"), "some")
    open_pairs = rest.drop("differ").join(some, LINE, "left_anti").join(likeliest, [*EARLY, *LINE], "left_anti")
    left = staging.table(open_pairs, "left")
    staging.drop("rest")
    more = staging.table(_verify(left, lines, staging, "left"), "more")
    similar = gone.union(some).union(more).withColumn("similar", F.lit(True))
    marked = staging.table(lines.select(*LINE).join(similar, LINE, "left"), "marked")
    for name in ("distinct", "near", "near-texts", "gone", "met", "likeliest", "likeliest-texts", "some", "left", "left-texts", "more"):
        staging.drop(name)
    return marked.groupBy("d", "r").agg(
        F.count(F.lit(1)).alias("n_first"), F.count("similar").alias("n_similar"),
        F.sort_array(F.collect_list(F.when(F.col("similar").isNull(), F.col("l")))).alias("kept_lines"),
    )


def _placed(docs: DataFrame, staging: Staging) -> DataFrame:
    """``docs`` with a place (d, r) of its own for each row."""
    place = F.coalesce("doc_id", F.lit((1 << 63) - 1))
    repeated = docs.groupBy(place.alias("d")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
    if repeated:
        return staging.table(docs, "rows", row_id="r").withColumn("d", place)
    return docs.withColumns({"d": place, "r": F.lit(0).cast("long")})


def _report(rows: DataFrame, staging: Staging) -> DataFrame:
    """``rows`` with n_lines, n_exact, n_similar, n_kept and kept_lines."""
    decided = _decide(rows.select("d", "r", "text"), staging)
    with_word = F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    joined = rows.withColumn("n_lines", F.coalesce(F.size(with_word), F.lit(0)).cast("long")).join(decided, ["d", "r"], "left")
    zero = F.lit(0).cast("long")
    firsts, similar = F.coalesce("n_first", zero), F.coalesce("n_similar", zero)
    return joined.withColumns(
        {
            "n_lines": F.greatest("n_lines", zero),
            "n_exact": F.greatest("n_lines", zero) - firsts,
            "n_similar": similar,
            "n_kept": firsts - similar,
            "kept_lines": F.coalesce("kept_lines", F.array().cast("array<int>")),
        }
    )


def line_report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_lines, n_exact, n_similar, n_kept, kept_lines) for every document.

    ``n_exact`` are repeats of an earlier equal line, ``n_similar`` other lines near an earlier
    one; ``kept_lines`` lists the numbers (from 0) of the lines with words that stay.
    """
    staging = Staging(docs.sparkSession, "lines")
    rows = _placed(docs.select("doc_id", "text"), staging)
    return _report(rows, staging).select("doc_id", "n_lines", "n_exact", "n_similar", "n_kept", "kept_lines")


def drop_similar_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with the later of equal and similar lines taken out of the text."""
    staging = Staging(docs.sparkSession, "lines")
    own, names = numbered(docs, "doc_id", "text")
    reported = _report(_placed(own, staging), staging)
    lines = F.split("text", "\n")
    blank = lambda x: squeezed(x) == ""
    kept = F.array_join(F.filter(lines, lambda x, i: blank(x) | F.array_contains("kept_lines", i)), "\n")
    at = names[docs.columns.index("text")]
    return reported.withColumn(at, F.when(F.col("text").isNull(), F.lit(None)).otherwise(kept)).select(*names).toDF(*docs.columns)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_report(documents(spark, sf_dir))
    return found.withColumn("kept_sha256", F.sha2(F.array_join("kept_lines", ","), 256)).drop("kept_lines")
