"""A derived corpus: questions over the given tables, and rollouts made from their gold SQL.

No language model is needed: a rollout is its question's SQL after seeded mutations, in
the fixed layout behind a rendered trace.  Everything is a function of ids and a seed,
so any partitioning and any retry gives the same corpus.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from densesql.functions.completion import CLOSE, OPEN
from densesql.operators.atoms import operations

# The questions as (database, difficulty, question, gold SQL), six for each database.
QUESTIONS = (
    ("sales", "simple", "How many orders are there for each priority?", "select o_orderpriority, count(*) from orders group by o_orderpriority"),
    ("sales", "simple", "Which customers belong to the building segment?", "select c_name from customer where c_mktsegment = 'BUILDING'"),
    ("sales", "moderate", "Which segments have sold for more than one million?", "select c_mktsegment, sum(o_totalprice) from customer join orders on c_custkey = o_custkey group by c_mktsegment having sum(o_totalprice) > 1000000"),
    ("sales", "moderate", "Who are the ten customers with the highest spend?", "select c_custkey, sum(o_totalprice) as spend from customer join orders on c_custkey = o_custkey group by c_custkey order by spend desc, c_custkey limit 10"),
    ("sales", "challenging", "Which orders cost more than the average of their own customer?", "select o.o_orderkey from orders o where o.o_totalprice > (select avg(i.o_totalprice) from orders i where i.o_custkey = o.o_custkey)"),
    ("sales", "challenging", "Which customers have never ordered?", "select c_custkey from customer except select o_custkey from orders"),
    ("supply", "simple", "Which parts have a size above forty?", "select p_partkey from part where p_size > 40"),
    ("supply", "simple", "Which types of part exist?", "select distinct p_type from part"),
    ("supply", "moderate", "What quantity comes from the suppliers of each nation?", "select n_name, sum(l_quantity) from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by n_name"),
    ("supply", "moderate", "Which parts were never shipped?", "select p.p_partkey from part p left join lineitem l on p.p_partkey = l.l_partkey where l.l_partkey is null"),
    ("supply", "challenging", "What are the names and revenues of the ten best suppliers?", "with best as (select l_suppkey, sum(l_quantity) as revenue from lineitem group by l_suppkey order by revenue desc, l_suppkey limit 10) select s_name, revenue from best join supplier on l_suppkey = s_suppkey"),
    ("supply", "challenging", "How does each supplier rank by balance in its nation?", "select s_suppkey, rank() over (partition by s_nationkey order by s_acctbal desc) from supplier"),
    ("geo", "simple", "How many nations has each region?", "select r_name, count(*) from region join nation on r_regionkey = n_regionkey group by r_name"),
    ("geo", "simple", "Which nations are in region one?", "select n_name from nation where n_regionkey = 1"),
    ("geo", "moderate", "How many customers live in each region?", "select r_name, count(*) from region join nation on r_regionkey = n_regionkey join customer on c_nationkey = n_nationkey group by r_name"),
    ("geo", "moderate", "What is the average balance in each segment?", "select c_mktsegment, avg(c_acctbal) from customer group by c_mktsegment"),
    ("geo", "challenging", "Which customers are richer than the mean of their nation?", "select c.c_name from customer c where c.c_acctbal > (select avg(d.c_acctbal) from customer d where d.c_nationkey = c.c_nationkey)"),
    ("geo", "challenging", "Which nations have both suppliers and customers?", "select s_nationkey from supplier intersect select c_nationkey from customer"),
    ("clicks", "simple", "How many events of each type are there?", "select event_type, count(*) from events group by event_type"),
    ("clicks", "simple", "What is the largest value?", "select max(value) from events"),
    ("clicks", "moderate", "How many events happened on each day?", "select cast(ts as date) as day, count(*) from events group by cast(ts as date)"),
    ("clicks", "moderate", "Which users met more than five errors?", "select user_id, count(*) from events where event_type = 'error' group by user_id having count(*) > 5"),
    ("clicks", "challenging", "How many sessions are there with gaps of an hour?", "select count(*) from (select ts, lag(ts) over (partition by user_id order by ts, event_id) as prev from events) t where prev is null or ts > prev + interval 1 hour"),
    ("clicks", "challenging", "How many purchases follow a view of the same user?", "select count(distinct p.event_id) from events v join events p on v.user_id = p.user_id and p.ts > v.ts where v.event_type = 'view' and p.event_type = 'purchase'"),
    ("docs", "simple", "How many documents are there in each language?", "select lang, count(*) from documents group by lang"),
    ("docs", "simple", "Which documents have no label?", "select d.doc_id from documents d left join labels l on d.doc_id = l.doc_id where l.doc_id is null"),
    ("docs", "moderate", "What share of each source is toxic?", "select d.source, avg(l.toxic) from documents d join labels l on d.doc_id = l.doc_id group by d.source"),
    ("docs", "moderate", "How long is the longest document of each language?", "select lang, max(n_chars) from documents group by lang"),
    ("docs", "challenging", "Which documents are longer than the mean of their source?", "select d.doc_id from documents d join (select source, avg(n_chars) as m from documents group by source) s on d.source = s.source where d.n_chars > s.m"),
    ("docs", "challenging", "Which documents have fewer than zero characters?", "select doc_id from documents where n_chars between -10 and -1"),
    ("chat", "simple", "How many turns has each role?", "select role, count(*) from conversations group by role"),
    ("chat", "simple", "How many conversations are there?", "select count(distinct conv_id) from conversations"),
    ("chat", "moderate", "Which conversations have more than six turns?", "select conv_id, count(*) from conversations group by conv_id having count(*) > 6"),
    ("chat", "moderate", "How long is the longest text of each role?", "select role, max(length(text)) from conversations group by role"),
    ("chat", "challenging", "How many turns are shorter than the next one?", "select count(*) from (select length(text) as n, lead(length(text)) over (partition by conv_id order by turn) as m from conversations) t where n < m"),
    ("chat", "challenging", "Which conversations are longer than the average one?", "with sizes as (select conv_id, count(*) as n from conversations group by conv_id) select conv_id from sizes where n > (select avg(n) from sizes)"),
    ("vectors", "simple", "How many vectors has each label?", "select label, count(*) from embeddings group by label"),
    ("vectors", "simple", "Which vectors have label three?", "select vec_id from embeddings where label = 3"),
    ("vectors", "moderate", "What are the first and last vector of each label?", "select label, min(vec_id), max(vec_id) from embeddings group by label"),
    ("vectors", "moderate", "Which labels have more than forty vectors?", "select label from embeddings group by label having count(*) > 40"),
    ("vectors", "challenging", "How many pairs share each label?", "select a.label, count(*) from embeddings a join embeddings b on a.label = b.label and a.vec_id < b.vec_id group by a.label"),
    ("vectors", "challenging", "Which are the first three vectors of each label?", "select vec_id from (select vec_id, row_number() over (partition by label order by vec_id) as r from embeddings) t where r <= 3"),
)

#: Chance that a rollout of a tier is mutated away from the gold; training changes which rollouts a policy samples, not these.
TIERS = {"s": 0.72, "m": 0.55, "l": 0.42}
#: Seed of the draw that references are taken from, apart from that of the scored rollouts; the teacher whose answers seed the memory.
REFERENCE_SEED, STRONGEST = 77, "plan"
TEACHERS = {"plan": 0.42, "story": 0.45, "clauses": 0.48, "terse": 0.5}
KEEPING = ("M01", "M02", "M03", "M04", "M05")
WRONG = ("M06", "M07", "M09", "M10", "M11", "M12", "M13", "M16")
FAILING = ("M08", "M14", "M15", "M20")
LAYOUT = ("M17", "M18", "M19", "M21", "M22")

ROLLOUT = (
    "question_id long, rollout_id int, db_id string, difficulty string, tier string, temperature double, style string, "
    "mutators array<string>, completion string, logp double"
)


def questions(spark: SparkSession) -> DataFrame:
    """(question_id, db_id, question, evidence, difficulty, gold_sql, split)."""
    rows = [(k, db, q, f"Tables of {db}.", level, sql, "dev" if draw(k, "split") < 0.2 else "train") for k, (db, level, q, sql) in enumerate(QUESTIONS)]
    return spark.createDataFrame(rows, "question_id long, db_id string, question string, evidence string, difficulty string, gold_sql string, split string")


def draw(*parts: object, seed: int = 42) -> float:
    """A repeatable uniform number in [0, 1) for the given names."""
    return (xxh64_intdigest("|".join(map(str, parts)), seed) >> 11) / (1 << 53)


def _first(pattern: str, to: str, sql: str) -> str:
    return re.sub(pattern, to, sql, count=1)


def mutate(sql: str, mutator: str, pick: float = 0.0) -> str:
    """The SQL after one mutation of the catalogue; unchanged where it does not apply."""
    if mutator == "M01":
        m = re.search(r"\b(?:from|join) \w+ (?!on\b|where\b|join\b|left\b|group\b|order\b|intersect\b|except\b|having\b)(\w+)\b", sql)
        return re.sub(rf"(?<![\w.]){m[1]}(?=\.|\s+on\b|\s+where\b|\s+join\b|\s+left\b|\s+group\b)", f"{m[1]}_x", sql) if m else sql
    if mutator == "M02":
        return _first(r"([A-Za-z_][\w.]*) = ([A-Za-z_][\w.]*)", r"\2 = \1", sql)
    if mutator == "M03":
        return _first(r"from (\w+) join (\w+) on", r"from \2 join \1 on", sql)
    if mutator == "M04":
        if " between " in sql:
            return _first(r"(\S+) between (\S+) and (\S+)", r"\1 >= \2 and \1 <= \3", sql)
        return _first(r"([A-Za-z_][\w.]*) = ('[^']*'|\d+)", r"(\1 = \2 or \1 = \2)", sql)
    if mutator == "M05":
        return sql if sql.startswith("with") or " limit " in sql or "count(" in sql.split(" from ")[0] else f"with answer as ({sql}) select * from answer"
    if mutator == "M06":
        return sql.replace("select distinct ", "select ", 1) if sql.startswith("select distinct ") else _first(r"^select ", "select distinct ", sql)
    if mutator == "M07":
        return _first(r"\b(avg|sum|max)\(", "count(", sql) if re.search(r"\b(avg|sum|max)\(", sql) else _first(r"count\(\*\)", "max(1)", sql)
    if mutator == "M08":
        return _first(r" group by [\w.]+(\([^)]*\))?", "", sql)
    if mutator == "M09":
        return _first(r"'[^']*'", "'none'", sql) if "'" in sql else _first(r"(?<![\w.])(\d+)\b", lambda m: str(int(m[1]) + 1), sql)
    if mutator == "M10":
        return _first(r" (>|<)(?=[ =])", lambda m: " " + {">": "<", "<": ">"}[m[1]], sql)
    if mutator == "M11":
        return _first(r" on ([\w.]+) = ([\w.]+)", r" on \1 = \2 + 1", sql)
    if mutator == "M12":
        return _first(r"(?<!left) join ", " left join ", sql)
    if mutator == "M13":
        return _first(r" (having|limit|order by) [^)]*$", "", sql)
    if mutator == "M14":
        return _first(r"^((?:with .*\) )?select (?:distinct )?)([\w.]+)", r"\1school_name", sql)
    if mutator == "M15":
        return sql.replace("select", "selct", 1) if pick < 0.5 or ")" not in sql else sql[: sql.rindex(")")] + sql[sql.rindex(")") + 1 :]
    if mutator == "M16":
        return f"select * from ({sql}) nothing where 1 = 0" if not sql.startswith("with") else sql
    if mutator == "M20":
        return "The answer is 42"
    if mutator == "M21":
        return f"{sql}; select 1"
    return sql


def render_trace(question: str, sql: str, style: str, length: float = 1.0) -> str:
    """Reasoning text about the SQL's operations in one of the teachers' styles, shortened by ``length``."""
    ops = [o for o in operations(sql) if not o.kind.startswith("subquery")]
    named = [f"{o.kind.replace('.', ' ')} {' '.join(o.args)}".strip() for o in ops] or ["give a direct answer"]
    head = f"The question asks: {question} "
    if style == "plan":
        body = " ".join(f"Step {k}: apply {x}, because the result needs {x.split(' ')[-1]}." for k, x in enumerate(named, 1))
    elif style == "story":
        body = "First look at the schema and decide what matters. " + " ".join(f"After that we use {x} so that the rows are right." for x in named)
    elif style == "clauses":
        body = " ".join(f"Clause {x.split(' ')[0]} takes {' and '.join(x.split(' ')[1:]) or 'nothing'}." for x in named)
    else:
        body = "; ".join(named) + "."
    text = head + body
    extra = f" Checking columns again: {', '.join(sorted({a for o in ops for a in o.args if a.isidentifier()}))}. The plan keeps every needed row and drops the others before the final statement."
    text += extra * max(0, round(4 * length) - 1)
    return text


def complete(question_id: int, variety: int, tier: str, style: str, key: str, error: float) -> tuple[list[str], str, float]:
    """(mutators, completion, mean log-probability) of one draw."""
    _, level, question, gold = QUESTIONS[question_id]
    at = (question_id, variety, tier, style, key)
    hard = {"simple": 0.75, "moderate": 1.0, "challenging": 1.2}[level]
    names, u = [], draw(*at, "error")
    if u < error * hard:
        kind = draw(*at, "kind")
        pool = WRONG if kind < 0.55 else FAILING if kind < 0.85 else LAYOUT
        names.append(pool[int(draw(*at, "which") * len(pool))])
    if draw(*at, "style") < 0.5:
        names.append(KEEPING[int(draw(*at, "keep") * len(KEEPING))])
    sql = gold
    for name in sorted(names, key=lambda n: n in WRONG + FAILING):
        sql = mutate(sql, name, draw(*at, name))
    trace = render_trace(question, sql, style, 0.25 + 0.75 * draw(*at, "length"))
    if "M18" in names:
        trace = ""
    if "M19" in names:
        trace = "We join the tables again. " * 40
    if "M22" in names:
        trace = " ".join([trace] * 40)
    text = f"{OPEN}{trace}{CLOSE}\n{sql}"
    if "M17" in names:
        text = text.replace(CLOSE, "", 1) if draw(*at, "tag") < 0.5 else f"Sure! {text}"
    return names or ["M00"], text, -0.2 - 0.6 * draw(*at, "logp") - 0.3 * bool(set(names) & set(WRONG + FAILING))


def rollouts(spark: SparkSession, group: int = 32, tier: str = "s", temperature: float = 1.0, seed: int = 42, partitions: int = 4) -> DataFrame:
    """``group`` rollouts of every question.  Temperature sets how many different draws a group holds: 0 means one."""
    n, variety = len(QUESTIONS), 1 + round(temperature * 31)
    styles = list(TEACHERS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for i in batch.column(0).to_pylist():
                q, r = divmod(i, group)
                at = r % variety
                style = styles[int(draw(q, at, tier, seed, "teacher") * len(styles))]
                names, text, logp = complete(q, at, tier, style, f"roll{seed}", TIERS[tier])
                rows.append((q, r, QUESTIONS[q][0], QUESTIONS[q][1], tier, temperature, style, names, text, logp))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    schema = to_arrow_schema(StructType.fromDDL(ROLLOUT))
    return spark.range(0, n * group, 1, partitions).mapInArrow(run, ROLLOUT)


def bank(spark: SparkSession, seeds: int = 1) -> DataFrame:
    """(question_id, teacher, seed, db_id, mutators, completion): every teacher answers every question, failures kept."""
    rows = []
    for q in range(len(QUESTIONS)):
        for teacher, error in TEACHERS.items():
            for s in range(seeds):
                names, text, _ = complete(q, s, teacher, teacher, "bank", error)
                rows.append((q, teacher, s, QUESTIONS[q][0], names, text))
    return spark.createDataFrame(rows, "question_id long, teacher string, seed int, db_id string, mutators array<string>, completion string")


def bank_stats(judged: DataFrame, price_per_million: float = 1.0) -> DataFrame:
    """(teacher, n, correct, accuracy, tokens, cost); the row with null teacher is the whole bank."""
    tokens = F.size(F.split(F.trim("completion"), r"\s+"))
    return judged.rollup("teacher").agg(
        F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("correct"), F.avg(F.col("correct").cast("double")).alias("accuracy"),
        F.sum(tokens).alias("tokens"), (F.sum(tokens) * F.lit(price_per_million / 1e6)).alias("cost"),
    )
