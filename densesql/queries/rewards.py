"""Layout, execution, totals, enrichment: the composite reward on tables, literals and the derived corpus."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import completion as C
from densesql.functions.similarity import SHAPES
from densesql.operators import corpus, enrich, execute, pipeline, rewards
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.sources.tables import load, table


@cache
def staged(app: str, sf_dir: str, tier: str = "s", temperature: float = 1.0, group: int = 32) -> DataFrame:
    """Scored rollouts, made once for each session, tables and setting."""
    spark = SparkSession.active()
    return pipeline.scored_rollouts(spark, sf_dir, tier, group, temperature)


def scored(spark: SparkSession, sf_dir: str, tier: str = "s", temperature: float = 1.0, group: int = 32) -> DataFrame:
    return staged(spark.sparkContext.applicationId, sf_dir, tier, temperature, group)


@query(
    "format_reward_pages",
    r"""with p as (select page_id, regexp_extract(html, '(?s)<article>(.*?)</article>', 1) as trace, (length(html) - length(replace(html, '<article>', ''))) // 9 as opens,
        (length(html) - length(replace(html, '</article>', ''))) // 10 as closes from pages)
    select page_id, cast(opens as integer) as opens, cast(closes as integer) as closes, length(trace) as n_chars,
        case when opens = 1 and closes = 1 and length(trim(trace)) > 0 then 1.0 else 0.0 end as reward from p""",
)
def format_reward_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The layout rule on markup-heavy text: exactly one article block with content."""
    html = F.col("html")
    trace = F.regexp_extract(html, r"(?s)<article>(.*?)</article>", 1)
    count = lambda t: ((F.length(html) - F.length(F.replace(html, F.lit(t), F.lit("")))) / len(t)).cast("int")
    opens, closes = count("<article>"), count("</article>")
    ok = (opens == 1) & (closes == 1) & (F.length(F.trim(trace)) > 0)
    return table(spark, sf_dir, "pages").select(
        "page_id", opens.alias("opens"), closes.alias("closes"), F.length(trace).cast("long").alias("n_chars"), rewards.format_reward(ok).alias("reward")
    )


COMPLETIONS = (
    ("well formed", "<think>a plan</think>\nselect 1", None),
    ("missing block", "select 1", "no_block"),
    ("unclosed", "<think>a plan\nselect 1", "unclosed"),
    ("two blocks", "<think>a</think><think>b</think>select 1", "many_blocks"),
    ("text before", "Sure! <think>a</think>select 1", "prefix_text"),
    ("empty sql", "<think>a</think>  ", "empty_sql"),
    ("two statements", "<think>a</think>select 1; select 2", "many_statements"),
    ("quoted semicolon", "<think>a</think>select ';' as x;", None),
    ("blank trace", "<think>  \n </think>select 1", "empty_trace"),
    ("answer text", "<think>a</think>The answer is 42", "not_a_query"),
    ("bracketed", "<think>a</think>(select 1) union (select 2)", None),
    ("reversed tags", "</think>a<think>select 1", "unclosed"),
)


@query(
    "format_reward_literals",
    "select conv_id, turn, name, cast(error as varchar) as error, case when error is null then 1.0 else 0.0 end as reward from conversations join (values "
    + ", ".join(f"({k}, '{n}', {'null' if e is None else repr(e)})" for k, (n, _, e) in enumerate(COMPLETIONS))
    + f") t(k, name, error) on (conv_id + turn) % {len(COMPLETIONS)} = k",
)
def format_reward_literals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every turn's words as the reasoning of a completion in one of the layouts."""
    rows = spark.createDataFrame([(k, n, t) for k, (n, t, _) in enumerate(COMPLETIONS)], "k long, name string, layout string")
    note = F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), "[^a-z]+", " ")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.pmod(F.col("conv_id") + F.col("turn"), F.lit(len(COMPLETIONS))).alias("k"), note.alias("note"))
    written = turns.join(F.broadcast(rows), "k").withColumn("completion", F.replace("layout", F.lit(f"{C.OPEN}a"), F.concat(F.lit(f"{C.OPEN}a "), "note")))
    return C.split(written).select("conv_id", "turn", "name", F.col("format_error").alias("error"), rewards.format_reward(F.col("format_ok")).alias("reward"))


@query(
    "format_reward_conv",
    """select conv_id, turn, role, case when length(trim(text)) > 0 and text not like '%<%' then 1.0 else 0.0 end as reward from conversations""",
)
def format_reward_conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    ok = (F.length(F.trim("text")) > 0) & ~F.col("text").contains("<")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", rewards.format_reward(F.coalesce(ok, F.lit(False))).alias("reward"))


# --- execution

GOLD_SQL = [(k, sql) for k, (_, _, _, sql) in enumerate(corpus.QUESTIONS)]


@query("gold_counts", " union all ".join(f"select cast({k} as bigint) as question_id, 'runs' as status, (select count(*) from ({sql})) as n_rows" for k, sql in GOLD_SQL))
def gold_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every gold statement runs, and how many rows it returns."""
    q = corpus.questions(spark)
    ran = execute.run(spark, sf_dir, q.select("db_id", F.col("gold_sql").alias("sql")))
    return q.join(ran, (q.db_id == ran.db_id) & (q.gold_sql == ran.sql)).select("question_id", "status", "n_rows")


#: (name, database, gold, prediction).
EXEC_PAIRS = (
    ("same", "geo", "select n_name from nation where n_regionkey = 1", "select n_name from nation where 1 = n_regionkey"),
    ("other filter", "geo", "select n_name from nation where n_regionkey = 1", "select n_name from nation where n_regionkey = 2"),
    ("distinct", "geo", "select n_regionkey from nation", "select distinct n_regionkey from nation"),
    ("reordered", "geo", "select n_name from nation order by n_name", "select n_name from nation order by n_name desc"),
    ("columns swapped", "geo", "select n_name, r_name from nation join region on n_regionkey = r_regionkey", "select r_name, n_name from nation join region on n_regionkey = r_regionkey"),
    ("average", "geo", "select c_mktsegment, avg(c_acctbal) from customer group by c_mktsegment", "select c_mktsegment, sum(c_acctbal) / count(*) from customer group by c_mktsegment"),
    ("between", "supply", "select p_partkey from part where p_size between 5 and 9", "select p_partkey from part where p_size >= 5 and p_size <= 9"),
    ("intersection", "geo", "select s_nationkey from supplier intersect select c_nationkey from customer", "select distinct s_nationkey from supplier where s_nationkey in (select c_nationkey from customer)"),
    ("nothing", "sales", "select c_custkey from customer where c_custkey < 0", "select c_custkey from customer where 1 = 0"),
)


def _sql_equal(a: str, b: str, mode: str) -> str:
    every = "all " if mode == "bag" else ""
    return f"not exists ((select * from ({a}) x except {every}select * from ({b}) y) union all (select * from ({b}) z except {every}select * from ({a}) w))"


@query(
    "exec_reward_modes",
    " union all ".join(
        f"select '{n}' as name, {_sql_equal(g, p, 'bag')} as bag_equal, {_sql_equal(g, p, 'set')} as set_equal" for n, _, g, p in EXEC_PAIRS if n != "average"
    ),
)
def exec_reward_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Result comparison as bags and as sets, exactly."""
    load(spark, sf_dir)
    rows = []
    for name, _, gold, sql in EXEC_PAIRS:
        if name != "average":
            a, b = spark.sql(gold), spark.sql(sql)
            rows.append((name, execute.compare(a, b, "bag"), execute.compare(a, b, "set")))
    return spark.createDataFrame(rows, "name string, bag_equal boolean, set_equal boolean")


@query("exec_digest_modes")
def exec_digest_modes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same comparisons by digest, with row order and with column order ignored."""
    load(spark, sf_dir)
    rows = []
    for name, _, gold, sql in EXEC_PAIRS:
        a, b = spark.sql(gold), spark.sql(sql)
        rows.append((name, tuple(execute.digest(a).first()) == tuple(execute.digest(b).first()), execute.compare(a, b, "ordered"), execute.compare(a, b, "bag_colperm")))
    return spark.createDataFrame(rows, "name string, bag boolean, ordered boolean, bag_colperm boolean")


def _exec_oracle(scheme: str) -> str:
    hit = 2.0 if scheme == "graded" else 1.0
    miss = 1.0 if scheme == "graded" else 0.0
    return " union all ".join(
        f"select '{n}' as name, case when {_sql_equal(g, p, 'bag')} then {hit} else {miss} end as reward" for n, _, g, p in EXEC_PAIRS if n != "average"
    )


def _exec(scheme: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        pairs = [(k, *p) for k, p in enumerate(EXEC_PAIRS) if p[0] != "average"]
        parsed = spark.createDataFrame([(k, n, d, s) for k, n, d, _, s in pairs], "question_id long, name string, db_id string, sql string")
        gold = spark.createDataFrame([(k, d, g) for k, _, d, g, _ in pairs], "question_id long, db_id string, gold_sql string")
        judged = execute.judge(spark, sf_dir, parsed, gold)
        return judged.select("name", rewards.exec_reward(F.col("status"), F.col("correct"), scheme).alias("reward"))

    return run


for _scheme in ("graded", "binary"):
    query(f"exec_reward_{_scheme}", _exec_oracle(_scheme))(_exec(_scheme))


@query("exec_status_classes")
def exec_status_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every way to fail: parse, analysis, run time, forbidden."""
    cases = [
        ("parse", "sales", "selct c_name from customer"), ("bracket", "sales", "select count(c_name from customer"), ("foreign column", "sales", "select n_name from customer"),
        ("foreign table", "sales", "select * from events"), ("no grouping", "sales", "select c_mktsegment, avg(c_acctbal) from customer"), ("division", "sales", "select 1 / 0 from customer"),
        ("path", "sales", "select * from parquet.`/root/testdata`"), ("reflection", "sales", "select java_method('java.lang.Math', 'abs', 1)"), ("command", "sales", "drop table customer"),
        ("runs", "sales", "select count(*) from customer"),
    ]
    df = spark.createDataFrame(cases, "name string, db_id string, sql string")
    ran = execute.run(spark, sf_dir, df)
    return df.join(ran, ["db_id", "sql"]).select("name", "status")


# --- totals

@query(
    "reward_total",
    """select l_orderkey, l_linenumber, l_partkey, round(case when l_returnflag = 'R' then 0 else 1 + case when l_linestatus = 'O' then 1 else 0 end
        + 0.05 * (l_quantity / 50.0) + 0.95 * 0.79 * pow(l_quantity / 50.0, 0.2) + l_discount * 10 end, 6) as total from lineitem""",
)
def reward_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line item as a wrong rollout: returned is malformed, open runs, quantity is overlap and discount closeness."""
    items = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_discount", "l_returnflag", "l_linestatus")
    parts = items.withColumns(
        {
            "format": rewards.format_reward(F.col("l_returnflag") != "R"),
            "exec": rewards.exec_reward(F.when(F.col("l_linestatus") == "O", "runs").otherwise("fails"), F.lit(False)),
            "atomic": rewards.atomic_reward(F.col("l_quantity") / 50.0, F.lit(False)),
            "mem": F.col("l_discount") * 10,
        }
    )
    return rewards.compose(parts).select("l_orderkey", "l_linenumber", "l_partkey", F.round("total", 6).alias("total"))


@query(
    "reward_separation",
    """with t as (select name, max(3 + mix * (l_quantity / 50.0) + (1 - mix) * cap * pow(l_quantity / 50.0, power)) as largest from lineitem, (values """
    + ", ".join(f"('{n}', {m}, {c}, {p})" for n, (m, c, p) in SHAPES.items())
    + ") s(name, mix, cap, power) group by name) select name, round(largest, 6) as largest_wrong, largest < 4 - 1e-12 as separates from t",
)
def reward_separation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest total of wrong rollouts that run and are close to the memory, quantity being overlap, under each shaping."""
    items = table(spark, sf_dir, "lineitem", "l_quantity").withColumns({c: F.lit(1.0) for c in ("format", "exec", "mem")})
    out = None
    for name in SHAPES:
        shaped = rewards.compose(items.withColumn("atomic", rewards.atomic_reward(F.col("l_quantity") / 50.0, F.lit(False), name)))
        row = shaped.agg(F.max("total").alias("largest")).select(F.lit(name).alias("name"), F.round("largest", 6).alias("largest_wrong"), (F.col("largest") < 4 - 1e-12).alias("separates"))
        out = row if out is None else out.union(row)
    return out


@query("reward_rollouts")
def reward_rollouts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every reward component of every rollout."""
    keep = ["format", "exec", "atomic", "mem", "total", "advantage"]
    return scored(spark, sf_dir).select("question_id", "rollout_id", "status", "correct", *[F.round(c, 6).alias(c) for c in keep])


@query("reward_gate_variants")
def reward_gate_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hard and soft layout gates, only-wrong and always-on overlap, both middle arms."""
    base = scored(spark, sf_dir)
    always = base.withColumn("atomic", rewards.atomic_reward(F.col("overlap"), F.col("correct"), only_wrong=False))
    from densesql.operators.memory import memory_reward

    strict = base.withColumn("mem", memory_reward(F.col("mem_score"), F.col("format_ok"), F.col("correct"), F.col("status") == "runs", "not_runnable"))
    parts = {"hard": rewards.compose(base), "soft": rewards.compose(base, gate="soft"), "always on": rewards.compose(always), "not runnable": rewards.compose(strict)}
    out = None
    for name, df in parts.items():
        row = df.agg(F.lit(name).alias("variant"), F.round(F.avg("total"), 6).alias("mean_total"), F.round(F.avg("mem"), 6).alias("mean_mem"), F.round(F.avg("atomic"), 6).alias("mean_atomic"))
        out = row if out is None else out.union(row)
    return out


@query("reward_scaling")
def reward_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = rewards.scaling_report(scored(spark, sf_dir))
    return found.select("class", "n", *[F.round(c, 6).alias(c) for c in (*rewards.COMPONENTS, "total")])


@query("hallucination_penalty")
def hallucination_penalty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What becomes of rollouts by mutation: foreign columns fail analysis and earn no execution reward."""
    each = scored(spark, sf_dir).select(F.explode("mutators").alias("mutator"), "status", "exec", "mem")
    return each.groupBy("mutator", "status").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("exec"), 6).alias("exec"), F.round(F.avg("mem"), 6).alias("mem"))


# --- reference pools


def _pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    return enrich.build_pool(corpus.questions(spark), scored(spark, sf_dir))


@query("enrich_pool")
def enrich_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """References a question after enrichment with verified samples."""
    return _pool(spark, sf_dir).groupBy("question_id").agg(F.count(F.lit(1)).alias("refs"), F.max("empty_result").alias("empty_result"))


@query("enrich_gold_only_contrast")
def enrich_gold_only_contrast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best overlap with the gold alone and with the pool: the pool is never worse."""
    from densesql.operators import atoms

    base = scored(spark, sf_dir)
    alone = atoms.best_reference(base, enrich.build_pool(corpus.questions(spark), None)).withColumnRenamed("overlap", "gold_only")
    both = base.select("question_id", "rollout_id", "overlap", "correct").join(alone.select("question_id", "rollout_id", "gold_only"), ["question_id", "rollout_id"])
    return both.groupBy("correct").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("gold_only"), 6).alias("gold_only"), F.round(F.avg("overlap"), 6).alias("pool"), F.count_if(F.col("overlap") < F.col("gold_only") - 1e-9).alias("worse")
    )


@query("empty_gold_rate")
def empty_gold_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return enrich.empty_rate(scored(spark, sf_dir)).select("n", "n_empty", F.round("share", 6).alias("share"))


@query("empty_guard")
def empty_guard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the guard takes out of the pools of questions whose gold result is empty."""
    pool = Staging(spark, "pool").table(_pool(spark, sf_dir), "pool")
    return pool.join(enrich.empty_guard(pool), ["question_id", "ref_id"], "left_anti").select("question_id", "ref_id", "sql")


@query("spurious_audit")
def spurious_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return enrich.audit(_pool(spark, sf_dir)).select("question_id", "ref_id", F.round("overlap", 6).alias("overlap"), "only_distinct")


@query("enrich_overlap")
def enrich_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = enrich.overlap_summary(_pool(spark, sf_dir))
    return found.select("n", *[F.round(c, 6).alias(c) for c in ("p10", "p50", "p90", "mean")])


@query("reward_baselines")
def reward_baselines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Partial and coarse rewards of other trainers on the same rollouts, by outcome."""
    gold = corpus.questions(spark).select("question_id", "gold_sql")
    pool = enrich.build_pool(corpus.questions(spark), None).select("question_id", F.col("op_keys").alias("gold_keys"))
    base = scored(spark, sf_dir).join(gold, "question_id").join(pool, "question_id")
    col = F.col
    both = base.withColumns(
        {
            "partial": rewards.partial_baseline(col("sql"), col("gold_sql"), col("op_keys"), col("gold_keys"), col("parsed"), col("correct")),
            "coarse": rewards.coarse_baseline(col("format_ok"), col("status"), col("correct"), col("trace")),
            "edit": rewards.edit_ratio(col("sql"), col("gold_sql")),
        }
    )
    return both.groupBy("status", "correct").agg(F.count(F.lit(1)).alias("n"), *[F.round(F.avg(c), 6).alias(c) for c in ("partial", "coarse", "edit", "total")])
