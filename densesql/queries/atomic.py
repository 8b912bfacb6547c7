"""Set overlap, shaping, references and the operation vocabulary."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.functions import similarity as S
from densesql.functions import text as T
from densesql.operators import atoms, corpus, rewards, setjoin
from densesql.queries import query
from densesql.sources.tables import table

_SETS = """
d as (select doc_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) as a, regexp_extract_all(lower(text), '[a-z0-9_]+') as bag from documents),
b as (select item_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) as b, regexp_extract_all(lower(text), '[a-z0-9_]+') as bag_b from benchmark),
dw as (select doc_id, unnest(a) as w from d), bw as (select item_id, unnest(b) as w from b),
common as (select doc_id, item_id, count(*) as n from dw join bw using (w) group by doc_id, item_id),
j as (select doc_id, item_id, n / cast(len(a) + len(b) - n as double) as overlap from common join d using (doc_id) join b using (item_id))
"""


def sets(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Documents as operation sets and benchmark items as references."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.array_distinct(T.tokens(F.col("text"))).alias("a"))
    items = table(spark, sf_dir, "benchmark").select("item_id", F.array_distinct(T.tokens(F.col("text"))).alias("b"))
    return docs, items


def overlaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, item_id, overlap) of every pair that shares a word: an equi-join on words, counted before anything else."""
    docs, items = sets(spark, sf_dir)
    shared = docs.select("doc_id", F.size("a").alias("na"), F.explode("a").alias("w")).join(
        items.select("item_id", F.size("b").alias("nb"), F.explode("b").alias("w")), "w"
    )
    counted = shared.groupBy("doc_id", "item_id", "na", "nb").agg(F.count(F.lit(1)).alias("n"))
    return counted.select("doc_id", "item_id", (F.col("n") / (F.col("na") + F.col("nb") - F.col("n"))).alias("overlap"))


@query("jaccard_docs_refs", f"with {_SETS} select doc_id, item_id, round(overlap, 6) as overlap from j where overlap >= 0.2")
def jaccard_docs_refs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return overlaps(spark, sf_dir).where("overlap >= 0.2").withColumn("overlap", F.round("overlap", 6))


@query(
    "best_reference",
    f"with {_SETS}, r as (select *, row_number() over (partition by doc_id order by round(overlap, 9) desc, item_id) as k from j) select doc_id, item_id, round(overlap, 6) as overlap from r where k = 1",
)
def best_reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    order = Window.partitionBy("doc_id").orderBy(F.round("overlap", 9).desc(), "item_id")
    best = overlaps(spark, sf_dir).withColumn("k", F.row_number().over(order)).where("k = 1")
    return best.select("doc_id", "item_id", F.round("overlap", 6).alias("overlap"))


@query(
    "jaccard_bag",
    """with e as (select conv_id, turn, regexp_extract_all(lower(text), '[a-z0-9_]+') as t from conversations),
    p as (select x.conv_id, x.turn, x.t as a, y.t as b from e x join e y on x.conv_id = y.conv_id and y.turn = x.turn + 1),
    k as (select conv_id, turn, a, b, unnest(list_distinct(list_concat(a, b))) as w from p),
    c as (select conv_id, turn, len(list_filter(a, lambda x: x = w)) as n, len(list_filter(b, lambda x: x = w)) as m from k)
    select conv_id, turn, round(sum(least(n, m)) / sum(greatest(n, m)), 6) as overlap from c group by conv_id, turn""",
)
def jaccard_bag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Multiset overlap of each turn with the next one."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", T.tokens(F.col("text")).alias("a"))
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("a").alias("b"))
    both = turns.join(after, ["conv_id", "turn"]).where((F.size("a") > 0) | (F.size("b") > 0))
    return both.select("conv_id", "turn", F.round(S.jaccard_bag(F.col("a"), F.col("b")), 6).alias("overlap"))


_SHAPE_ROWS = ", ".join(f"('{n}', {m}, {c}, {p})" for n, (m, c, p) in S.SHAPES.items())


@query(
    "shape_curve_s1_s4",
    f"""select name, i / 20.0 as x, round({{}}, 6) as y from (values {_SHAPE_ROWS}) s(name, mix, cap, power), range(0, 21) t(i)""".format(
        "mix * (i / 20.0) + (1 - mix) * cap * pow(i / 20.0, power)"
    ).replace("i / 20.0 as x", "cast(i / 20.0 as double) as x"),
)
def shape_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    grid = spark.range(21).select((F.col("id") / 20.0).alias("x"))
    parts = [grid.select(F.lit(n).alias("name"), "x", F.round(S.shape_named(F.col("x"), n), 6).alias("y")) for n in S.SHAPES]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@query(
    "shape_histogram",
    f"""with {_SETS}, m as (select doc_id, max(overlap) as x from j group by doc_id)
    select name, cast(floor((mix * x + (1 - mix) * cap * pow(x, power)) * 10) as bigint) as bin, count(*) as n
    from m, (values {_SHAPE_ROWS}) s(name, mix, cap, power) group by 1, 2""",
)
def shape_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How each shaping spreads the best overlap of every document: one scan, four columns."""
    best = overlaps(spark, sf_dir).groupBy("doc_id").agg(F.max("overlap").alias("x"))
    each = best.select(F.inline(F.array(*[F.struct(F.lit(n).alias("name"), S.shape_named(F.col("x"), n).alias("y")) for n in S.SHAPES])))
    return each.groupBy("name", F.floor(F.col("y") * 10).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query(
    "simjoin_prefix",
    """with d as (select doc_id, list_distinct(regexp_extract_all(lower(text), '[a-z0-9_]+')) as a from documents),
    w as (select doc_id, len(a) as n, unnest(a) as w from d),
    c as (select x.doc_id as left_id, y.doc_id as right_id, x.n as nx, y.n as ny, count(*) as k from w x join w y on x.w = y.w and x.doc_id < y.doc_id
        and least(x.n, y.n) >= 0.8 * greatest(x.n, y.n) group by all)
    select left_id, right_id, round(k / cast(nx + ny - k as double), 6) as overlap from c where k >= 0.8 * (nx + ny - k) - 1e-9""",
)
def simjoin_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All document pairs whose word sets overlap by 0.8, without comparing all pairs."""
    docs = setjoin.word_sets(table(spark, sf_dir, "documents", "doc_id", "text"), "doc_id", "text", "a")
    return setjoin.prefix_join(docs, "doc_id", "a", 0.8).select("left_id", "right_id", F.round("overlap", 6).alias("overlap"))


@query("minhash_join")
def minhash_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, _ = sets(spark, sf_dir)
    return setjoin.minhash_join(docs, "doc_id", "a", 0.8).select("left_id", "right_id", F.round("overlap", 6).alias("overlap"))


# --- SQL structure

#: Pairs of (name, gold, prediction) and their expected shared and total operations.
PAIRS = (
    ("identical", "select c_name from customer where c_acctbal > 5", "select c_name from customer where c_acctbal > 5", 3, 3),
    ("average to count", "select c_mktsegment, avg(c_acctbal) from customer group by c_mktsegment", "select c_mktsegment, count(*) from customer group by c_mktsegment", 3, 5),
    ("no grouping", "select c_mktsegment, avg(c_acctbal) from customer group by c_mktsegment", "select c_mktsegment, avg(c_acctbal) from customer", 3, 4),
    ("unbalanced", "select c_name from customer", "select c_name from (customer", 0, 2),
    ("distinct added", "select c_mktsegment from customer", "select distinct c_mktsegment from customer", 2, 3),
    ("direction flipped", "select c_name from customer order by c_acctbal", "select c_name from customer order by c_acctbal desc", 2, 4),
    ("foreign column", "select c_name from customer", "select l_tax from customer", 1, 3),
)


def asked(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """(event_id, k): every event as a rollout, with the number of the statement it is about."""
    return table(spark, sf_dir, "events", "event_id").select("event_id", F.pmod("event_id", F.lit(n)).alias("k"))


def rollout_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, name, gold, sql): every event as a rollout of one of PAIRS."""
    rows = spark.createDataFrame([(k, *p[:3]) for k, p in enumerate(PAIRS)], "k long, name string, gold string, sql string")
    return asked(spark, sf_dir, len(PAIRS)).join(F.broadcast(rows), "k").drop("k")


@query(
    "atomic_reward_sql",
    "select event_id, name, round(shared / cast(total as double), 6) as overlap, round(case when shared = 0 then 0 else 0.05 * shared / total + 0.95 * 0.79 * pow(shared / cast(total as double), 0.2) end, 6) as reward from events join (values "
    + ", ".join(f"({k}, '{n}', {s}, {t})" for k, (n, _, _, s, t) in enumerate(PAIRS))
    + f") p(k, name, shared, total) on event_id % {len(PAIRS)} = k",
)
def atomic_reward_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overlap reward of the statement of every rollout in the event log."""
    rows = rollout_pairs(spark, sf_dir)
    gold = atoms.decompose(rows.select("event_id", F.col("gold").alias("sql")), "sql").select("event_id", F.col("op_keys").alias("gold_keys"))
    both = atoms.decompose(rows.select("event_id", "name", "sql"), "sql").join(gold, "event_id")
    overlap = S.jaccard(F.col("op_keys"), F.col("gold_keys"))
    return both.select("event_id", "name", F.round(overlap, 6).alias("overlap"), F.round(rewards.atomic_reward(overlap, F.lit(False)), 6).alias("reward"))


@query(
    "op_diff_by_kind",
    """select event_id, kind, cast(hit as bigint) as hit, cast(miss as bigint) as miss, cast(extra as bigint) as extra
    from events, (values ('group.key', 1, 0, 0), ('select.aggregate', 0, 1, 1), ('select.column', 1, 0, 0), ('from.table', 1, 0, 0)) t(kind, hit, miss, extra)"""
    + f" where event_id % {len(PAIRS)} = 1",
)
def op_diff_by_kind(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The worked example, counting instead of averaging, for every rollout of it in the event log."""
    rows = rollout_pairs(spark, sf_dir).where(F.col("name") == PAIRS[1][0])
    mine, gold = (atoms.decompose(rows.select("event_id", F.col(c).alias("sql")), "sql") for c in ("sql", "gold"))
    return atoms.diff(mine, gold, ("event_id",)).select("event_id", "kind", "hit", "miss", "extra")


@query("op_vocabulary")
def op_vocabulary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often each kind occurs in the gold statements of the questions that the event log asks."""
    gold = corpus.questions(spark).select(F.col("question_id").alias("k"), F.col("gold_sql").alias("sql"))
    log = asked(spark, sf_dir, len(corpus.QUESTIONS)).join(F.broadcast(gold), "k")
    ops = atoms.decompose(log, "sql").select(F.col("k").alias("question_id"), F.explode("ops.kind").alias("kind"))
    return ops.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("question_id").alias("questions"))


@query("op_options_variants")
def op_options_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alias, commutation, marker and literal options: overlap of meaning-keeping mutations, as the event log draws them, with the gold under each."""
    texts = [(m, sql, corpus.mutate(sql, m)) for *_, sql in corpus.QUESTIONS for m in corpus.KEEPING]
    rows = spark.createDataFrame([(k, *t) for k, t in enumerate(texts)], "k long, mutator string, gold string, sql string")
    pairs = asked(spark, sf_dir, len(texts)).join(F.broadcast(rows), "k")
    variants = {
        "surface": atoms.Options(), "resolved": atoms.Options(alias="resolved"), "resolved+commute": atoms.Options(alias="resolved", commute=True),
        "no markers": atoms.Options(markers=False), "separate literals": atoms.Options(consts="separate"),
    }
    out = None
    for name, options in variants.items():
        mine = atoms.decompose(pairs, "sql", options).select("mutator", "gold", "op_keys")
        theirs = atoms.decompose(pairs.select("gold").distinct(), "gold", options).select("gold", F.col("op_keys").alias("gold_keys"))
        part = mine.join(theirs, "gold").groupBy("mutator").agg(F.round(F.avg(S.jaccard(F.col("op_keys"), F.col("gold_keys"))), 6).alias("overlap"))
        part = part.select(F.lit(name).alias("options"), "mutator", "overlap")
        out = part if out is None else out.union(part)
    return out


@query(
    "ngram_baseline",
    """with e as (select conv_id, turn, regexp_extract_all(lower(text), '[a-z0-9_]+') as t from conversations),
    g as (select conv_id, turn, list_distinct(list_transform(range(1, len(t)), lambda i: t[i] || ' ' || t[i + 1])) as g from e),
    p as (select x.conv_id, x.turn, x.g as a, y.g as b from g x join g y on x.conv_id = y.conv_id and y.turn = x.turn + 1)
    select conv_id, turn, round(coalesce(len(list_intersect(a, b)) / nullif(cast(len(list_distinct(list_concat(a, b))) as double), 0), 0), 6) as overlap from p""",
)
def ngram_baseline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shared word pairs of each turn with the next one."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.coalesce("text", F.lit("")).alias("text"))
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("next"))
    return turns.join(after, ["conv_id", "turn"]).select("conv_id", "turn", F.round(rewards.ngram_jaccard(F.col("text"), F.col("next")), 6).alias("overlap"))
