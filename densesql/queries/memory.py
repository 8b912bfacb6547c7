"""Memory look-ups, rewards, gates and upkeep on embeddings and documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.functions import vec
from densesql.operators import ann, embed
from densesql.operators import memory as M
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.sources.tables import memory_from_embeddings, table

KS = (1, 5, 10, 20, 30)

_SIMS = """
v as (select vec_id, cast(label as varchar) as db_id, cast(embedding as double[]) as e from embeddings),
sims as (
    select q.vec_id as query_id, q.db_id as q_db, m.vec_id as entry_id, m.db_id as m_db,
        round(list_inner_product(q.e, m.e) / (sqrt(list_inner_product(q.e, q.e)) * sqrt(list_inner_product(m.e, m.e))), 9) as cos
    from v q join v m on q.vec_id <> m.vec_id and {scope}
), ranked as (
    select *, row_number() over (partition by query_id order by cos desc, entry_id) as rank from sims
)
"""
_SCOPE_SQL = {"cross": "q.db_id <> m.db_id", "same": "q.db_id = m.db_id", "mixed": "true"}


def sims(scope: str) -> str:
    return _SIMS.format(scope=_SCOPE_SQL[scope])


_CENTRE = """
parts as (
    select query_id, i, avg(e[i]) as c, max(q.e_i) as t from (
        select r.query_id, m.e, q.e as qe, i, q.e[i] as e_i from ranked r join v m on m.vec_id = r.entry_id
        join v q on q.vec_id = r.query_id, range(1, 65) t(i) where r.rank <= 20) q group by query_id, i
), scored as (
    select query_id, sum(t * c) / (sqrt(sum(t * t)) * sqrt(sum(c * c))) as score from parts group by query_id
)
"""


def vectors(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    memory = memory_from_embeddings(spark, sf_dir)
    return memory.withColumnRenamed("entry_id", "query_id"), memory


def clustered_vectors(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """``vectors`` with an offset that each label's share, which gives them the structure of a memory of topics."""
    q, m = vectors(spark, sf_dir)
    unit = lambda i: F.pmod(F.xxhash64(F.lit("offset"), "db_id", i), F.lit(1 << 20)) / float(1 << 19) - 1.0
    moved = F.transform("embedding", lambda x, i: (x.cast("double") + 0.3 * unit(i)).cast("float"))
    return q.withColumn("embedding", moved), m.withColumn("embedding", moved)


def _lookup(scope: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        q, m = vectors(spark, sf_dir)
        return M.lookup(q, m, 20, scope).select("query_id", "entry_id", F.round("cos", 6).alias("cos"), "rank")

    return run


for _scope in M.SCOPES:
    query(
        f"mem_lookup_{_scope}_k20",
        f"with {sims(_scope)} select query_id, entry_id, round(cos, 6) as cos, cast(rank as integer) as rank from ranked where rank <= 20",
    )(_lookup(_scope))


@query("mem_lookup_join_plan", f"with {sims('same')} select query_id, entry_id, round(cos, 6) as cos, cast(rank as integer) as rank from ranked where rank <= 5")
def mem_lookup_join_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, m = vectors(spark, sf_dir)
    return M.lookup_join(q, m, 5, "same").select("query_id", "entry_id", F.round(F.round("cos", 9), 6).alias("cos"), "rank")


@query(
    "mem_sweep_k",
    f"""with {sims("cross")} select k, count(*) as n, round(avg(cos), 6) as mean_cos, round(min(cos), 6) as least_cos
    from ranked, (values (1), (5), (10), (20), (30)) t(k) where rank <= k group by k""",
)
def mem_sweep_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, m = vectors(spark, sf_dir)
    swept = M.sweep(M.lookup(q, m, max(KS), "cross"), KS)
    return swept.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("cos"), 6).alias("mean_cos"), F.round(F.min("cos"), 6).alias("least_cos"))


@query("mem_centroid_reward", f"with {sims('cross')}, {_CENTRE} select query_id, round(score, 6) as score from scored")
def mem_centroid_reward(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, m = vectors(spark, sf_dir)
    return M.scores(q, M.lookup(q, m, 20, "cross"), m).select("query_id", F.round("score", 6).alias("score"))


def _flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels as outcomes of the rollout with the same number: quality is correctness, toxic a broken layout."""
    return table(spark, sf_dir, "labels").select(F.col("doc_id").alias("query_id"), (F.col("quality") == 1).alias("correct"), (F.col("toxic") == 1).alias("malformed"))


@query(
    "mem_reward_three_arms",
    f"""with {sims("cross")}, {_CENTRE} select s.query_id,
        case when coalesce(l.toxic, 0) = 1 then 'malformed' when coalesce(l.quality, 0) = 1 then 'correct' else 'scored' end as arm,
        round(case when coalesce(l.toxic, 0) = 1 then 0 when coalesce(l.quality, 0) = 1 then 1 else s.score end, 6) as reward
    from scored s left join labels l on l.doc_id = s.query_id""",
)
def mem_reward_three_arms(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, m = vectors(spark, sf_dir)
    scored = M.scores(q, M.lookup(q, m, 20, "cross"), m).join(_flags(spark, sf_dir), "query_id", "left").fillna(False, ["correct", "malformed"])
    reward = M.memory_reward(F.col("score"), ~F.col("malformed"), F.col("correct"))
    arm = F.when(F.col("malformed"), "malformed").when(F.col("correct"), "correct").otherwise("scored")
    return scored.select("query_id", arm.alias("arm"), F.round(reward, 6).alias("reward"))


@query(
    "mem_pooling_variants",
    f"""with {sims("cross")}, {_CENTRE} select s.query_id, round(s.score, 6) as centroid, round(max(r.cos), 6) as best, round(avg(r.cos), 6) as mean
    from scored s join ranked r on r.query_id = s.query_id and r.rank <= 20 group by s.query_id, s.score""",
)
def mem_pooling_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, m = vectors(spark, sf_dir)
    found = M.lookup(q, m, 20, "cross")
    pooled = M.centroid(found, m).join(q.select("query_id", vec.doubles(F.col("embedding")).alias("q_vec")), "query_id")
    value = vec.cosine(F.col("q_vec"), F.col("centroid"))
    return pooled.select("query_id", F.round(value, 6).alias("centroid"), F.round("max_cos", 6).alias("best"), F.round("mean_cos", 6).alias("mean"))


@query(
    "mem_scope_mix_share",
    f"""with {sims("mixed")} select k, count_if(q_db = m_db) as same_db, count(*) as n, round(avg(case when q_db = m_db then 1.0 else 0.0 end), 6) as share
    from ranked, (values (1), (5), (10), (20), (30)) t(k) where rank <= k group by k""",
)
def mem_scope_mix_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How much of the neighbourhood comes from the query's own database when all are allowed."""
    q, m = vectors(spark, sf_dir)
    found = M.lookup(q, m, max(KS), "mixed").join(q.select("query_id", F.col("db_id").alias("q_db")), "query_id")
    found = found.join(m.select("entry_id", F.col("db_id").alias("m_db")), "entry_id")
    same = F.col("q_db") == F.col("m_db")
    return M.sweep(found, KS).groupBy("k").agg(
        F.count_if(same).alias("same_db"), F.count(F.lit(1)).alias("n"), F.round(F.avg(same.cast("double")), 6).alias("share")
    )


@query(
    "mem_scope_k_grid",
    " union all ".join(
        f"select * from (with {sims(s)}, c as (select query_id, k, avg(cos) as mean from ranked, (values (1), (5), (10), (20), (30)) t(k) where rank <= k group by query_id, k) "
        f"select '{s}' as scope, k, round(avg(mean), 6) as mean_cos from c group by k)"
        for s in M.SCOPES
    ),
)
def mem_scope_k_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neighbourhood similarity for every scope and k: three rankings, prefixes of each."""
    q, m = vectors(spark, sf_dir)
    parts = []
    for scope in M.SCOPES:
        per = M.sweep(M.lookup(q, m, max(KS), scope), KS).groupBy("query_id", "k").agg(F.avg("cos").alias("mean"))
        parts.append(per.groupBy("k").agg(F.round(F.avg("mean"), 6).alias("mean_cos")).select(F.lit(scope).alias("scope"), "k", "mean_cos"))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


# --- gates ------------------------------------------------------------------------------

LEXICON = """
lex as (
    select list(word order by word) as words from (
        select word from (select unnest(regexp_extract_all(lower(text), '[a-z0-9_]+')) as word from benchmark)
        where length(word) >= 3 group by word order by count(*) desc, word limit 40)
), d as (
    select doc_id, source, regexp_extract_all(lower(text), '[a-z0-9_]+') as toks from documents
), g as (
    select doc_id, source, len(toks) as n, len(list_filter(toks, lambda t: list_contains(words, t))) as hits,
        len(list_intersect(list_distinct(toks), words)) as distinct_hits,
        case when len(toks) < 2 then 1.0 else cast(len(list_distinct(list_transform(range(1, len(toks)), lambda i: toks[i] || ' ' || toks[i + 1]))) as double) / (len(toks) - 1) end as diversity
    from d, lex
), r as (
    select *, case when n < 30 then 'short' when n > 2000 then 'long' when coalesce(cast(hits as double) / nullif(n, 0), 0) < 0.05 then 'density'
        when distinct_hits < 2 then 'distinct' when diversity < 0.6 then 'diversity' else 'accepted' end as reason from g
)
"""


def lexicon(spark: SparkSession, sf_dir: str, n: int = 40) -> DataFrame:
    """One row: the commonest words of three letters or more of the benchmark, standing for column names."""
    words = table(spark, sf_dir, "benchmark", "text").select(F.explode(T.tokens(F.col("text"))).alias("word")).where(F.length("word") >= 3)
    top = words.groupBy("word").count().orderBy(F.desc("count"), "word").limit(n)
    return top.agg(F.sort_array(F.collect_list("word")).alias("words"))


def traces(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "text")
    words = F.array(*map(F.lit, lexicon(spark, sf_dir).first()["words"]))  # at most 40 words
    return docs.select("doc_id", "source", T.tokens(F.col("text")).alias("toks")).withColumn("words", words)


@query("gate_length", f"with {LEXICON} select doc_id, n as n_tokens, n between 30 and 2000 as passed from g")
def gate_length(spark: SparkSession, sf_dir: str) -> DataFrame:
    return traces(spark, sf_dir).select("doc_id", F.size("toks").cast("long").alias("n_tokens"), T.gate_length(F.col("toks")).alias("passed"))


@query(
    "gate_density",
    f"with {LEXICON} select doc_id, round(coalesce(cast(hits as double) / nullif(n, 0), 0), 6) as density, cast(distinct_hits as integer) as distinct_hits from g",
)
def gate_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    t, w = F.col("toks"), F.col("words")
    return traces(spark, sf_dir).select("doc_id", F.round(T.density(t, w), 6).alias("density"), T.distinct_mentions(t, w).alias("distinct_hits"))


@query("gate_diversity", f"with {LEXICON} select doc_id, round(diversity, 6) as diversity, diversity >= 0.6 as passed from g")
def gate_diversity(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.col("toks")
    return traces(spark, sf_dir).select("doc_id", F.round(T.diversity(t), 6).alias("diversity"), T.gate_diversity(t).alias("passed"))


@query("gate_all_reasons", f"with {LEXICON} select reason, count(*) as n from r group by reason")
def gate_all_reasons(spark: SparkSession, sf_dir: str) -> DataFrame:
    return traces(spark, sf_dir).groupBy(T.gate_reason(F.col("toks"), F.col("words")).alias("reason")).agg(F.count(F.lit(1)).alias("n"))


@query(
    "mem_growth_batches",
    f"""with {LEXICON}, b as (select r.*, ntile(10) over (order by doc_id) as batch from r)
    select batch, case when coalesce(quality, 0) <> 1 then 'unverified' else reason end as reason, count(*) as n
    from b left join labels using (doc_id) group by 1, 2""",
)
def mem_growth_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten batches of traces in id order: what each admits and why the rest is turned away."""
    reasons = traces(spark, sf_dir).select("doc_id", T.gate_reason(F.col("toks"), F.col("words")).alias("reason"))
    batches = reasons.withColumn("batch", F.ntile(10).over(Window.orderBy("doc_id")))
    judged = batches.join(table(spark, sf_dir, "labels", "doc_id", "quality"), "doc_id", "left")
    reason = F.when(F.coalesce("quality", F.lit(0)) != 1, "unverified").otherwise(F.col("reason"))
    return judged.groupBy("batch", reason.alias("reason")).agg(F.count(F.lit(1)).alias("n"))


@query("seed_verified", "select source as db_id, count(*) as n, min(doc_id) as first_entry from documents join labels using (doc_id) where quality = 1 and toxic = 0 group by source")
def seed_verified(spark: SparkSession, sf_dir: str) -> DataFrame:
    bank = table(spark, sf_dir, "documents", "doc_id", "source").join(table(spark, sf_dir, "labels"), "doc_id")
    bank = bank.withColumn("verified", (F.col("quality") == 1) & (F.col("toxic") == 0)).withColumn("teacher", F.lit("t1"))
    return M.seed(bank, "t1").groupBy(F.col("source").alias("db_id")).agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first_entry"))


# --- near-duplicate skip ----------------------------------------------------------------

#: The given vectors are far apart, so the threshold is lowered until it has work to do.
TAU = 0.4


def _halves(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Labels 0-4 are the store, the others the arriving batch."""
    q, m = vectors(spark, sf_dir)
    return q.where(F.col("db_id").cast("int") >= 5), m.where(F.col("db_id").cast("int") < 5)


@query(
    "dedup_existing",
    f"""with {sims("mixed")} select vec_id as query_id from v where cast(db_id as integer) >= 5 and vec_id not in (
        select query_id from sims where cast(q_db as integer) >= 5 and cast(m_db as integer) < 5 and cos >= {TAU})""",
)
def dedup_existing(spark: SparkSession, sf_dir: str) -> DataFrame:
    new, store = _halves(spark, sf_dir)
    return M.dedup(new, store, TAU, "existing_only").select("query_id")


@query("dedup_greedy")
def dedup_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    new, store = _halves(spark, sf_dir)
    return M.dedup(new, store, TAU, "greedy_in_order").select("query_id")


@query("dedup_blocked_greedy")
def dedup_blocked_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    new, store = _halves(spark, sf_dir)
    return M.dedup(new, store, TAU, "blocked_greedy").select("query_id")


# --- index ------------------------------------------------------------------------------


def _recall(spark: SparkSession, sf_dir: str, index: str, clustered: bool) -> DataFrame:
    """Recall of the ten nearest for vectors whose id is divisible by 50, against all, and the share of pairs that was scored.

    The given vectors have hardly any structure, so an index must look nearly everywhere; with
    their label's offset added they have the structure that an index lives from.
    """
    q, m = clustered_vectors(spark, sf_dir) if clustered else vectors(spark, sf_dir)
    q = q.where("query_id % 50 = 0")
    exact = M.lookup(q, m, 10, "mixed")
    staging = Staging(spark, "recall")
    if index == "ivf":
        entries, centres = ann.build_ivf(m, 12)
        built = (staging.table(entries, "entries"), centres)
        probes = ann.calibrate_probes(ann.fitting_sample(m), centres, 10, 0.97)
        pairs = staging.table(ann.ivf_pairs(q, built, probes, "mixed"), "pairs")
        found = ann.completed(q, ann.ranked(pairs, 10), 10, lambda starved: ann.ivf_pairs(starved, built, len(centres), "mixed"))
        scored = pairs.agg(F.count(F.lit(1)).alias("n"))
    else:
        best = staging.table(ann.srp_best(q, m, 10, "mixed", 4, 24), "best")
        found = ann.completed(q, best.drop("scored"), 10, lambda starved: ann.srp_best(starved, m, 10, "mixed", 0, 1).drop("rank", "scored"))
        scored = best.where("rank = 1").agg(F.coalesce(F.sum("scored"), F.lit(0)).alias("n"))
    share = scored.select((F.col("n") / F.lit(max(1, q.count() * m.count()))).alias("scored"))
    recall = ann.recall_at_k(found, exact).crossJoin(share)  # one row each
    return recall.select(F.lit(index).alias("index"), F.lit("clustered" if clustered else "given").alias("vectors"), "k", "n_queries", F.round("recall", 6).alias("recall"), F.round("scored", 6).alias("scored"))


@query("ann_ivf_recall")
def ann_ivf_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _recall(spark, sf_dir, "ivf", False).union(_recall(spark, sf_dir, "ivf", True))


@query("ann_srp_recall")
def ann_srp_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _recall(spark, sf_dir, "srp", False)


@query("mem_text_lookup")
def mem_text_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Memory reward of hashed documents against the verified ones of other sources."""
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "text")
    encoded = Staging(spark, "traces").table(embed.encode(docs, "doc_id", "text", dims=128, keep=("source",)), "encoded")
    labels = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    store = encoded.join(labels, "doc_id", "left_semi").select(F.col("doc_id").alias("entry_id"), F.col("source").alias("db_id"), "embedding")
    asked = encoded.select(F.col("doc_id").alias("query_id"), F.col("source").alias("db_id"), "embedding")
    return M.scores(asked, M.lookup(asked, store, 20, "cross"), store).select("query_id", F.round("score", 6).alias("score"))
