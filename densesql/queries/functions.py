"""Scalar, array, map, JSON, date and URL functions, and the SQL surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.functions.registry import register_functions
from densesql.queries import query
from densesql.sources.tables import load, table


@query(
    "fn_strings",
    r"""select o_orderkey, lower(o_orderpriority) as l, substr(o_orderpriority, 1, 3) as s, length(o_orderpriority) as n, replace(o_orderpriority, '-', '_') as r, split_part(o_orderpriority, '-', 2) as p,
        levenshtein(o_orderpriority, '1-URGENT') as d, lpad(o_orderstatus, 3, '*') as q, regexp_extract(o_orderpriority, '([0-9]+)', 1) as x, translate(o_orderpriority, 'AEIOU', 'aeiou') as t from orders""",
)
def fn_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = F.col("o_orderpriority")
    long = lambda c: c.cast("long")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", F.lower(p).alias("l"), F.substring(p, 1, 3).alias("s"), long(F.length(p)).alias("n"), F.replace(p, F.lit("-"), F.lit("_")).alias("r"),
        F.split_part(p, F.lit("-"), F.lit(2)).alias("p"), long(F.levenshtein(p, F.lit("1-URGENT"))).alias("d"), F.lpad("o_orderstatus", 3, "*").alias("q"),
        F.regexp_extract(p, "([0-9]+)", 1).alias("x"), F.translate(p, "AEIOU", "aeiou").alias("t"),
    )


@query("fn_regexp", r"select page_id, len(regexp_extract_all(html, '<p>')) as paragraphs, regexp_replace(url, '^[a-z]+://', '') as bare, regexp_matches(url, '\?') as asked from pages")
def fn_regexp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(
        "page_id", F.regexp_count("html", F.lit("<p>")).cast("long").alias("paragraphs"), F.regexp_replace("url", "^[a-z]+://", "").alias("bare"), F.col("url").rlike(r"\?").alias("asked")
    )


@query(
    "fn_dates",
    """select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, year(o_orderdate) as y, quarter(o_orderdate) as q, dayofyear(o_orderdate) as d,
        date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as since, strftime(o_orderdate + interval 3 month, '%Y-%m-%d') as later from orders""",
)
def fn_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    long = lambda c: c.cast("long")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month"), long(F.year(d)).alias("y"), long(F.quarter(d)).alias("q"), long(F.dayofyear(d)).alias("d"),
        long(F.datediff(d, F.lit("1995-01-01").cast("date"))).alias("since"), F.date_format(F.add_months(d, 3), "yyyy-MM-dd").alias("later"),
    )


@query(
    "fn_math",
    "select s_suppkey, round(pow(s_nationkey, 1.5), 6) as p, round(ln(s_suppkey + 1), 6) as l, round(exp(-s_nationkey / 10.0), 6) as e, greatest(s_acctbal, 0) as g, cast(s_suppkey % 7 as bigint) as m, round(s_acctbal / nullif(s_nationkey, 0), 6) as d from supplier",
)
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("s_nationkey")
    return table(spark, sf_dir, "supplier").select(
        "s_suppkey", F.round(F.pow(n, F.lit(1.5)), 6).alias("p"), F.round(F.log(F.col("s_suppkey") + 1), 6).alias("l"), F.round(F.exp(-n / 10.0), 6).alias("e"),
        F.greatest("s_acctbal", F.lit(0.0)).alias("g"), F.pmod("s_suppkey", F.lit(7)).cast("long").alias("m"), F.round(F.try_divide("s_acctbal", n), 6).alias("d"),
    )


@query("fn_hash", "select doc_id, md5(text) as m, sha256(text) as s from documents")
def fn_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("m"), F.sha2(F.col("text").cast("binary"), 256).alias("s"))


@query(
    "fn_arrays",
    """with e as (select vec_id, cast(embedding as double[]) as v from embeddings)
    select vec_id, round(v[1], 6) as head, round(list_sum(v), 6) as total, len(list_filter(v, lambda x: x > 0)) as positive, round(list_max(v), 6) as top, round(list_sum(list_transform(v[1:8], lambda x: x * x)), 6) as square,
        list_position(list_transform(v, lambda x: x = list_max(v)), true) as at from e""",
)
def fn_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("embedding").cast("array<double>")
    add = lambda c: F.aggregate(c, F.lit(0.0), lambda s, x: s + x)
    return table(spark, sf_dir, "embeddings").select(
        "vec_id", F.round(F.element_at(v, 1), 6).alias("head"), F.round(add(v), 6).alias("total"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"),
        F.round(F.array_max(v), 6).alias("top"), F.round(add(F.transform(F.slice(v, 1, 8), lambda x: x * x)), 6).alias("square"), F.array_position(v, F.array_max(v)).alias("at"),
    )


@query(
    "fn_maps",
    "select o_custkey, count(distinct o_orderstatus) as kinds, count(*) filter (where o_orderstatus = 'O') as open from orders group by o_custkey",
)
def fn_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = table(spark, sf_dir, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
    m = counts.groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))
    return m.select("o_custkey", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("O")), F.lit(0)).alias("open"))


@query("fn_json", "select event_id, cast(json_extract(props, '$.k') as bigint) * 2 as twice, json_valid(props) as valid from events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = F.from_json("props", "map<string,bigint>")
    return table(spark, sf_dir, "events").select("event_id", (m["k"] * 2).alias("twice"), F.try_parse_json("props").isNotNull().alias("valid"))


@query("fn_urls", r"select page_id, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, nullif(regexp_extract(url, '\?([^#]*)', 1), '') as query from pages")
def fn_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = F.col("url")
    return table(spark, sf_dir, "pages").select(
        "page_id", F.try_parse_url(u, F.lit("PROTOCOL")).alias("scheme"), F.try_parse_url(u, F.lit("HOST")).alias("host"), F.try_parse_url(u, F.lit("QUERY")).alias("query")
    )


@query(
    "text_ngrams",
    """with t as (select doc_id, regexp_extract_all(lower(text), '[a-z0-9_]+') as t from documents)
    select doc_id, len(t) as tokens, len(list_distinct(t)) as types, greatest(len(t) - 2, 0) as trigrams from t""",
)
def text_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "documents").select("doc_id", T.tokens(F.col("text")).alias("t"))
    size = lambda c: F.size(c).cast("long")
    return t.select("doc_id", size(F.col("t")).alias("tokens"), size(F.array_distinct("t")).alias("types"), size(T.ngrams(F.col("t"), 3)).alias("trigrams"))


@query("sql_surface", "select doc_id, length(text) between 100 and 900 as passed, round(0.05 * 0.5 + 0.95 * 0.79 * pow(0.5, 0.2), 6) as shaped from documents")
def sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The methods called from SQL text by their registered names."""
    register_functions(spark)
    load(spark, sf_dir, ("documents",))
    return spark.sql("select doc_id, length(text) between 100 and 900 as passed, round(shape_reward(atomic_jaccard(array('a', 'b'), array('b')), 0.05, 0.79, 0.2), 6) as shaped from documents")


@query("sql_surface_udtf")
def sql_surface_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Operations of statements as a table function."""
    register_functions(spark)
    return spark.sql("select q.id, o.kind, o.key from values (1, 'select a, count(*) from t group by a') q(id, sql), lateral atoms(q.sql) o")
