"""Length, diversity, latency, memory and price measures; schema ranking."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.operators import corpus, cost, metrics, prompts, schema_filter
from densesql.queries import query
from densesql.queries.rewards import scored
from densesql.queries.selection import log
from densesql.sources.tables import DATABASES, schema_columns, schema_references, table


@query(
    "trace_length_by_role",
    """select role, count(*) as n, round(avg(length(text)), 6) as mean, round(quantile_cont(length(text), 0.5), 6) as p50, max(length(text)) as longest,
        round(avg(case when length(text) > 8000 then 1.0 else 0.0 end), 6) as over from conversations group by role""",
)
def trace_length_by_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = metrics.trace_length(table(spark, sf_dir, "conversations"), ("role",), "text")
    return found.select("role", "n", F.round("mean", 6).alias("mean"), F.round("p50", 6).alias("p50"), F.col("longest").cast("long").alias("longest"), F.round("over", 6).alias("over"))


@query(
    "trace_length_hist",
    """with b as (select case when length(text) >= 8000 then 17 else length(text) * 16 // 8000 + 1 end as bin from documents) select bin, count(*) as n from b group by bin""",
)
def trace_length_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.length_histogram(table(spark, sf_dir, "documents", "text"), "text")


@query("self_bleu_sources")
def self_bleu_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Self-BLEU of each source's documents."""
    return metrics.self_bleu(table(spark, sf_dir, "documents", "source", "text"), "source", "text").withColumn("self_bleu", F.round("self_bleu", 6))


@query("bank_diversity")
def bank_diversity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Self-BLEU within one teacher's style and across all styles."""
    bank = corpus.bank(spark, 3).select("teacher", "question_id", F.col("completion").alias("trace"))
    within = metrics.self_bleu(bank, "teacher").select(F.col("teacher").alias("group"), F.round("self_bleu", 6).alias("self_bleu"))
    across = metrics.self_bleu(bank.withColumn("group", F.concat(F.lit("question "), F.col("question_id"))), "group")
    return within.union(across.agg(F.lit("across styles").alias("group"), F.round(F.avg("self_bleu"), 6).alias("self_bleu")))


@query(
    "self_bleu2_sql",
    """with t as (select source, doc_id, regexp_extract_all(lower(text), '[a-z0-9_]+') as t from documents),
    g as (select source, doc_id, unnest(list_transform(range(1, len(t)), lambda i: t[i] || ' ' || t[i + 1])) as g from t where len(t) > 1),
    c as (select source, doc_id, g, count(*) as c from g group by all),
    r as (select *, max(c) over (partition by source, g) as top, row_number() over (partition by source, g order by c desc, doc_id) as r,
        coalesce(nth_value(c, 2) over (partition by source, g order by c desc, doc_id rows between unbounded preceding and unbounded following), 0) as second from c),
    p as (select source, doc_id, sum(least(c, case when r = 1 then second else top end)) / cast(sum(c) as double) as p from r group by all)
    select source, count(*) as k, round(avg(p), 6) as overlap from p group by source""",
)
def self_bleu2_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = metrics.self_overlap(table(spark, sf_dir, "documents", "source", "doc_id", "text"), "source", "doc_id", "text")
    return found.withColumn("overlap", F.round("overlap", 6))


_LATENCY = "count(*) as n, round(sum(value), 6) as total, round(avg(value), 6) as mean, round(quantile_cont(value, 0.5), 6) as p50, round(quantile_cont(value, 0.95), 6) as p95"


def _rounded(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in ("total", "mean", "p50", "p95")})


@query("latency_by_type", f"select event_type, {_LATENCY} from events group by event_type")
def latency_by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(cost.latency(table(spark, sf_dir, "events").select("event_type", F.col("value").alias("seconds")), ("event_type",)))


@query("latency_sketch")
def latency_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(cost.latency(table(spark, sf_dir, "events").select("event_type", F.col("value").alias("seconds")), ("event_type",), approximate=True))


@query(
    "latency_curve",
    """with c as (select user_id, row_number() over (partition by user_id order by ts, event_id) as i, value from events),
    s as (select user_id, k, sum(value) as seconds from c, (values (1), (10), (20), (30), (50)) t(k) where i <= k group by 1, 2)
    select k, count(*) as n, round(sum(seconds), 6) as total, round(avg(seconds), 6) as mean, round(quantile_cont(seconds, 0.5), 6) as p50, round(quantile_cont(seconds, 0.95), 6) as p95 from s group by k""",
)
def latency_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cumulative seconds of the first k candidates of a question."""
    c = log(spark, sf_dir).withColumn("k", F.explode(F.array(*map(F.lit, (1, 10, 20, 30, 50))))).where(F.col("rollout_id") < F.col("k"))
    return _rounded(cost.latency(c.groupBy("question_id", "k").agg(F.sum("value").alias("seconds")), ("k",)))


@query(
    "vram_table",
    "select tier, context, round(p * 2 + 2 * layers * heads * dim * context * 2.0 * 30 / 1e9 + 1.5, 6) as gb from (values "
    + ", ".join(f"('{n}', {p}, {la}, {h}, {d})" for n, p, la, h, d in cost.MODELS)
    + ") m(tier, p, layers, heads, dim), (values (2048), (4096), (8192)) c(context)",
)
def vram_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.vram_table(spark).withColumn("gb", F.round("gb", 6))


@query(
    "token_cost",
    """select role, count(*) as requests, cast(sum(ceil(length(text) / 4.0)) as bigint) as tokens, round(avg(ceil(length(text) / 4.0)), 6) as mean_tokens,
        round(sum(ceil(length(text) / 4.0)) * 2.5 / 1e6, 6) as cost from conversations group by role""",
)
def token_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = cost.tokens(table(spark, sf_dir, "conversations"), "text", 2.5, ("role",))
    return found.select("role", "requests", "tokens", F.round("mean_tokens", 6).alias("mean_tokens"), F.round("cost", 6).alias("cost"))


@query("verifier_cost", "select n, round(n * 0.24, 6) as cost from (values (1000), (10000)) t(n)")
def verifier_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(1000,), (10000,)], "n int").withColumn("cost", F.round(cost.verifier(F.col("n")), 6))


@query("distillation_cost", "select count(*) as samples, round(count(*) * 30 / 37600.0, 6) as cost from documents join labels using (doc_id) where quality = 1 and toxic = 0")
def distillation_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The price of the verified documents, were each a sample of a teacher."""
    verified = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0")
    return cost.distillation(table(spark, sf_dir, "documents", "doc_id").join(verified, "doc_id")).select("samples", F.round("cost", 6).alias("cost"))


@query(
    "ablation_delta",
    """with r as (select event_type as variant, cast(user_id % 3 as varchar) as tier, avg(value) as ex from events group by 1, 2),
    f as (select tier, ex as full_ex from r where variant = 'view')
    select r.tier, variant, round(ex, 6) as ex, round(ex - full_ex, 6) as delta from r join f on r.tier = f.tier""",
)
def ablation_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Differences of event types from one of them, as of reward variants from the full reward."""
    e = table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("variant"), (F.col("user_id") % 3).cast("string").alias("tier")).agg(F.avg("value").alias("ex"))
    return metrics.ablation_delta(e, "view").select("tier", "variant", F.round("ex", 6).alias("ex"), F.round("delta", 6).alias("delta"))


@query("corpus_profile", "select 'documents' as name, count(*) as n from documents union all select 'orders', count(*) from orders union all select 'events', count(*) from events")
def corpus_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [table(spark, sf_dir, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n")) for t in ("documents", "orders", "events")]
    return parts[0].union(parts[1]).union(parts[2])


# --- schemas and prompts


def _wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All databases merged into one wide schema, each table once."""
    cols = schema_columns(spark, sf_dir).dropDuplicates(["table_name", "column_name"])
    return cols.withColumn("db_id", F.lit("all"))


def _asked(spark: SparkSession) -> DataFrame:
    return corpus.questions(spark).select("question_id", F.lit("all").alias("db_id"), "question", "gold_sql")


def _gold_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = F.array_distinct(F.filter(F.split(F.lower("gold_sql"), "[^a-z0-9_]+"), lambda w: w != ""))
    used = corpus.questions(spark).select("question_id", "db_id", F.explode(words).alias("column_name"))
    return used.join(schema_columns(spark, sf_dir).select("db_id", "column_name").distinct(), ["db_id", "column_name"]).select("question_id", "column_name")


@query("schema_tfidf_recall")
def schema_tfidf_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the gold columns among the best of the merged schema, by both scorers."""
    out = None
    for scorer in ("tfidf", "bm25"):
        found = schema_filter.recall(schema_filter.rank(_asked(spark), _wide(spark, sf_dir), 30, scorer), _gold_columns(spark, sf_dir))
        row = found.select(F.lit(scorer).alias("scorer"), "k", F.round("recall", 6).alias("recall"))
        out = row if out is None else out.union(row)
    return out


@query("schema_tfidf_top30")
def schema_tfidf_top30(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = schema_filter.rank(_asked(spark), _wide(spark, sf_dir), 30)
    return found.select("question_id", "table_name", "column_name", F.round("score", 6).alias("score"), "place")


@query("schema_bm25_closure")
def schema_bm25_closure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The filtered schema of each question's own database with the keys between kept tables."""
    asked = corpus.questions(spark).select("question_id", "db_id", "question")
    found = schema_filter.rank(asked, schema_columns(spark, sf_dir), 6, "bm25", schema_references(spark))
    return found.select("question_id", "table_name", "column_name", F.round("score", 6).alias("score"), "place")


@query("prompts")
def prompt_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One prompt for every user turn, as a question to one of the databases, with both system messages."""
    names = F.array(*map(F.lit, DATABASES))
    turns = table(spark, sf_dir, "conversations").where("role = 'user'")
    asked = turns.select(
        F.concat_ws("-", "conv_id", "turn").alias("question_id"),
        F.element_at(names, (F.pmod("conv_id", F.lit(len(DATABASES))) + 1).cast("int")).alias("db_id"),
        F.coalesce("text", F.lit("")).alias("question"),
    ).withColumn("evidence", F.format_string("Tables of %s.", "db_id"))
    rows = prompts.render_user_prompt(asked, schema_columns(spark, sf_dir), schema_references(spark))
    return rows.select("question_id", "user_prompt", F.lit(prompts.system_message()).alias("tagged"), F.lit(prompts.system_message("native")).alias("native"))
