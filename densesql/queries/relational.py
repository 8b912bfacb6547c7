"""Scans, projections, joins, aggregates, windows, sorts and set operations on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.operators import relational as R
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.sources import tables
from densesql.sources.tables import table


@query("scan_parquet", "select l_orderkey, l_quantity, l_tax from lineitem where l_quantity > 45")
def scan_parquet(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity", "l_tax").where("l_quantity > 45")


@query("scan_json_props", "select event_id, cast(json_extract_string(props, '$.k') as integer) as k from events")
def scan_json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("scan_csv_round_trip", "select n_nationkey, n_name, n_regionkey from nation")
def scan_csv_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging, nation = Staging(spark, "csv"), table(spark, sf_dir, "nation")
    tables.write(nation, staging.path("nation"), "csv")
    return spark.read.schema(nation.schema).option("header", True).csv(staging.path("nation"))


@query("scan_json_lines", "select region.r_regionkey as id, region.r_name as name, false as corrupt from region union all select null, null, true")
def scan_json_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """JSON lines with one broken line, which is kept as such."""
    staging = Staging(spark, "json")
    good = table(spark, sf_dir, "region").select(F.to_json(F.struct(F.col("r_regionkey").alias("id"), F.col("r_name").alias("name"))).alias("value"))
    good.union(spark.createDataFrame([("{broken",)], "value string")).write.text(staging.path("lines"))
    rows = tables.read_rollouts(spark, staging.path("lines"), schema="id int, name string")
    return rows.select("id", "name", F.col("_corrupt").isNotNull().alias("corrupt"))


@query("sink_partitioned", "select o_orderstatus, count(*) as n from orders group by o_orderstatus")
def sink_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "sink")
    tables.write(table(spark, sf_dir, "orders"), staging.path("orders"), partition_by=("o_orderstatus",), sort_by=("o_orderkey",))
    return spark.read.parquet(staging.path("orders")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query("sink_orc", "select r_regionkey, r_name from region")
def sink_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "orc")
    tables.write(table(spark, sf_dir, "region"), staging.path("region"), "orc")
    return spark.read.orc(staging.path("region"))


@query("rollout_source", "select cast(i // 4 as bigint) as question_id, cast(i % 4 as integer) as rollout_id from range(0, 168) t(i)")
def rollout_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The generated corpus as a data source, split by ranges of questions."""
    from densesql.sources.rollouts import register

    register(spark)
    return spark.read.format("derived_rollouts").option("group", 4).load().select("question_id", "rollout_id")


@query("project_expr", "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) as charge from lineitem")
def project_expr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").selectExpr("l_orderkey", "l_linenumber", "round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) as charge")


@query("filter_forms", "select p_partkey from part where p_brand in ('Brand#1', 'Brand#2', 'Brand#11', 'Brand#12', 'Brand#13') and p_size between 5 and 30 and p_type like '%E%' and p_name is not null")
def filter_forms(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part")
    keep = F.col("p_brand").isin("Brand#1", "Brand#2", "Brand#11", "Brand#12", "Brand#13") & F.col("p_size").between(5, 30) & F.col("p_type").like("%E%") & F.col("p_name").isNotNull()
    return p.where(keep).select("p_partkey")


@query("filter_rlike", "select page_id from pages where regexp_matches(url, '^https?://(www|m)\\.')")
def filter_rlike(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").where(F.col("url").rlike(r"^https?://(www|m)\.")).select("page_id")


@query("null_safe_eq", "select d.doc_id, l.quality is not distinct from null as unlabelled, l.quality is not distinct from 1 as good from documents d left join labels l on d.doc_id = l.doc_id")
def null_safe_eq(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents", "doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    return d.select("doc_id", F.col("quality").eqNullSafe(F.lit(None)).alias("unlabelled"), F.col("quality").eqNullSafe(1).alias("good"))


@query("case_arms", "select event_id, case when value < 10 then 'low' when value < 50 then 'mid' else 'high' end as band from events")
def case_arms(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    return table(spark, sf_dir, "events").select("event_id", F.when(v < 10, "low").when(v < 50, "mid").otherwise("high").alias("band"))


@query("lateral_alias", "select l_orderkey, l_linenumber, round(l_extendedprice * 2, 4) as a, round(l_extendedprice * 2 + 1, 4) as b from lineitem where l_linenumber = 1")
def lateral_alias(spark: SparkSession, sf_dir: str) -> DataFrame:
    tables.load(spark, sf_dir, ("lineitem",))
    return spark.sql("select l_orderkey, l_linenumber, round(l_extendedprice * 2, 4) as a, round(l_extendedprice * 2 + 1, 4) as b from lineitem where l_linenumber = 1")


# --- joins


@query("join_broadcast", "select p_brand, count(*) as n, round(sum(l_quantity), 4) as q from lineitem join part on l_partkey = p_partkey group by p_brand")
def join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    joined = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part"), F.col("l_partkey") == F.col("p_partkey"))
    return joined.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"))


_MERGE = "select o_orderpriority, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority"


def _join(hint: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        o = table(spark, sf_dir, "orders").hint(hint)
        joined = table(spark, sf_dir, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
        return joined.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))

    return run


query("join_merge", _MERGE)(_join("merge"))
query("join_shuffle_hash", _MERGE)(_join("shuffle_hash"))


@query("join_salted", _MERGE)
def join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber").withColumnRenamed("l_orderkey", "o_orderkey")
    joined = R.salted_join(li, table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority"), "o_orderkey")
    return joined.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("join_full_outer", "select lang, quality, count(*) as n from documents full join labels on documents.doc_id = labels.doc_id group by lang, quality")
def join_full_outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents", "doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "full").groupBy("lang", "quality").agg(F.count(F.lit(1)).alias("n"))


@query("join_semi", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)")
def join_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").where("o_totalprice > 400000")
    return table(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("join_anti", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)")
def join_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").where("o_totalprice > 400000")
    return table(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("join_theta", "select a.r_name as a, b.r_name as b from region a join region b on a.r_regionkey < b.r_regionkey")
def join_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = (table(spark, sf_dir, "region").select(F.col("r_regionkey").alias(f"{s}k"), F.col("r_name").alias(s)) for s in "ab")
    return a.join(F.broadcast(b), F.col("ak") < F.col("bk")).select("a", "b")  # five rows


@query(
    "join_range",
    "select v.event_id as view_id, p.event_id as purchase_id from events v join events p on v.user_id = p.user_id and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour where v.event_type = 'view' and p.event_type = 'purchase'",
)
def join_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    v = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("t0"))
    p = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("t1"))
    return R.range_join(v, p, "user_id", "t0", "t1", 3600).select("view_id", "purchase_id")


@query(
    "join_asof",
    """select p.event_id, v.value as asof_value from (select * from events where event_type = 'purchase') p asof left join (select user_id, ts, max(value) as value from events where event_type = 'view' group by user_id, ts) v
    on p.user_id = v.user_id and p.ts >= v.ts""",
)
def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    p = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    v = e.where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return R.asof_join(p, v, "user_id", "ts", "value").select("event_id", "asof_value")


@query("join_lateral_topk", "select n_name, c_custkey, c_acctbal from nation, lateral (select c_custkey, c_acctbal from customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 3)")
def join_lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = R.top_k_per_key(table(spark, sf_dir, "customer"), ["c_nationkey"], [F.desc("c_acctbal"), F.col("c_custkey")], 3)
    return table(spark, sf_dir, "nation").join(c, F.col("n_nationkey") == F.col("c_nationkey")).select("n_name", "c_custkey", "c_acctbal")


# --- aggregates


@query(
    "agg_basic",
    """select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 4) as s, round(avg(l_extendedprice), 4) as a, min(l_shipdate) as first_ship, max(l_discount) as d,
        round(stddev_pop(l_quantity), 6) as sd from lineitem group by all""",
)
def agg_basic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 4).alias("s"), F.round(F.avg("l_extendedprice"), 4).alias("a"), F.min("l_shipdate").alias("first_ship"),
        F.max("l_discount").alias("d"), F.round(F.stddev_pop("l_quantity"), 6).alias("sd"),
    )


@query("agg_distinct", "select event_type, count(distinct user_id) as users, count(distinct cast(ts as date)) as days from events group by event_type")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("sketched"))


@query("agg_filtered", "select user_id, count(*) filter (where event_type = 'error') as errors, round(sum(value) filter (where event_type = 'purchase'), 4) as spent from events group by user_id")
def agg_filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return e.groupBy("user_id").agg(F.count_if(F.col("event_type") == "error").alias("errors"), F.round(F.sum(F.when(F.col("event_type") == "purchase", F.col("value"))), 4).alias("spent"))


@query("agg_collect_bounded", "select l_orderkey, array_to_string(list_sort(list_distinct(list(l_returnflag))), ',') as flags from lineitem group by l_orderkey")
def agg_collect_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.sort_array(F.collect_set("l_returnflag")), ",").alias("flags"))


@query("agg_percentile", "select lang, round(quantile_cont(n_chars, 0.5), 6) as p50, round(quantile_cont(n_chars, 0.9), 6) as p90 from documents group by lang")
def agg_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("lang").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("n_chars", F.lit(0.9)), 6).alias("p90"))


@query("agg_percentile_sketch")
def agg_percentile_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("lang").agg(F.percentile_approx("n_chars", F.lit(0.5), 1000).alias("p50"))


@query("agg_argmax", "select o_custkey, arg_max(o_orderkey, struct_pack(a := o_totalprice, b := -o_orderkey)) as top_order from orders group by o_custkey")
def agg_argmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", -F.col("o_orderkey"))).alias("top_order"))


@query("agg_mode", "with c as (select user_id, event_type, count(*) as n from events group by all) select user_id, arg_min(event_type, struct_pack(a := -n, b := event_type)) as usual from c group by user_id")
def agg_mode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The commonest type of each user; ties to the smaller name."""
    c = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return c.groupBy("user_id").agg(F.min_by("event_type", F.struct(-F.col("n"), "event_type")).alias("usual"))


@query("agg_rollup", "select o_orderstatus, o_orderpriority, count(*) as n, cast(grouping(o_orderstatus) as integer) as g from orders group by rollup (o_orderstatus, o_orderpriority)")
def agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping("o_orderstatus").cast("int").alias("g"))


@query("agg_cube", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)")
def agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("agg_grouping_sets", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders")
    return o.groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("agg_pivot", "select cast(ts as date)::varchar as day, count(*) filter (where event_type = 'view') as views, count(*) filter (where event_type = 'error') as errors from events group by 1")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "events").groupBy(F.to_date("ts").cast("string").alias("day")).pivot("event_type", ["view", "error"]).agg(F.count(F.lit(1)))
    return p.select("day", F.coalesce("view", F.lit(0)).alias("views"), F.coalesce("error", F.lit(0)).alias("errors"))


@query("agg_unpivot", "select s_suppkey, 'balance' as measure, s_acctbal as value from supplier union all select s_suppkey, 'nation', cast(s_nationkey as double) from supplier")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_acctbal").alias("balance"), F.col("s_nationkey").cast("double").alias("nation"))
    return s.unpivot("s_suppkey", ["balance", "nation"], "measure", "value")


@query("agg_regression", "select l_returnflag, round(corr(l_extendedprice, l_quantity), 6) as c, round(regr_slope(l_extendedprice, l_quantity), 6) as slope from lineitem group by l_returnflag")
def agg_regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem")
    return li.groupBy("l_returnflag").agg(F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("c"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 6).alias("slope"))


@query("agg_histogram", "select cast(n_chars // 500 as bigint) as bin, count(*) as n from documents group by 1")
def agg_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy(F.floor(F.col("n_chars") / 500).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query("agg_fingerprint", "select true as equal_to_shuffled, false as equal_to_distinct")
def agg_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_tax")
    x, y, z = (R.fingerprint(df).select(F.col("n").alias(f"n{k}"), F.col("h").alias(f"h{k}")) for k, df in enumerate((a, a.repartition(5, "l_tax"), a.distinct())))
    all_three = x.crossJoin(y).crossJoin(z)  # one row each
    return all_three.select(((F.col("n0") == F.col("n1")) & (F.col("h0") == F.col("h1"))).alias("equal_to_shuffled"), ((F.col("n0") == F.col("n2")) & (F.col("h0") == F.col("h2"))).alias("equal_to_distinct"))


# --- windows


@query(
    "win_rank_family",
    """select c_custkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, ntile(4) over w as nt, round(percent_rank() over v, 6) as pr, round(cume_dist() over v, 6) as cd
    from customer window w as (partition by c_nationkey order by c_acctbal, c_custkey), v as (partition by c_nationkey order by c_mktsegment)""",
)
def win_rank_family(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, v = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    long = lambda c: c.cast("long")
    return table(spark, sf_dir, "customer").select(
        "c_custkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(v)).alias("rk"), long(F.dense_rank().over(v)).alias("dr"), long(F.ntile(4).over(w)).alias("nt"),
        F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"),
    )


@query(
    "win_lag_lead",
    """select event_id, lag(value, 1) over w as before, lead(value, 2) over w as after, first_value(event_type) over w as first_type, nth_value(value, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second
    from events window w as (partition by user_id order by ts, event_id)""",
)
def win_lag_lead(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "events").select(
        "event_id", F.lag("value", 1).over(w).alias("before"), F.lead("value", 2).over(w).alias("after"), F.first("event_type").over(w).alias("first_type"), F.nth_value("value", 2).over(whole).alias("second")
    )


@query(
    "win_running_moving",
    """select event_id, round(sum(value) over (w rows between unbounded preceding and current row), 6) as running, round(avg(value) over (w rows between 4 preceding and current row), 6) as moving
    from events window w as (partition by user_id order by ts, event_id)""",
)
def win_running_moving(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select(
        "event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("running"), F.round(F.avg("value").over(w.rowsBetween(-4, 0)), 6).alias("moving")
    )


@query("win_range_interval", "select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as last_day from events")
def win_range_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count(F.lit(1)).over(w).alias("last_day"))


@query("win_group_stats", "select o_orderkey, round(o_totalprice - avg(o_totalprice) over (partition by o_custkey), 7) as above from orders")
def win_group_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", F.round(F.col("o_totalprice") - F.avg("o_totalprice").over(Window.partitionBy("o_custkey")), 7).alias("above"))


# --- sorts, samples, sets


@query("sort_limit", "select l_orderkey, l_linenumber, l_extendedprice from lineitem order by l_extendedprice desc, l_orderkey, l_linenumber limit 20")
def sort_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A top-20 report."""
    return table(spark, sf_dir, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(20).select("l_orderkey", "l_linenumber", "l_extendedprice")


@query("sort_offset", "select o_orderkey from orders order by o_totalprice, o_orderkey limit 10 offset 25")
def sort_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One page of a sorted report."""
    return table(spark, sf_dir, "orders").orderBy("o_totalprice", "o_orderkey").offset(25).limit(10).select("o_orderkey")


@query("topk_per_key", "select o_custkey, o_orderkey, cast(r as integer) as rank from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 2")
def topk_per_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.top_k_per_key(table(spark, sf_dir, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.col("o_orderkey")], 2).select("o_custkey", "o_orderkey", "rank")


@query("sample_hash", "select doc_id from documents order by md5(cast(doc_id as varchar)), doc_id limit 50")
def sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sampling operator: 50 documents, repeatable."""
    return R.hash_sample(table(spark, sf_dir, "documents", "doc_id"), "doc_id", 50)


@query("sample_stratified", "select lang, doc_id from (select *, row_number() over (partition by lang order by md5(cast(doc_id as varchar)), doc_id) as r from documents) where r <= 10")
def sample_stratified(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sampling operator: ten documents of each language."""
    return R.hash_sample(table(spark, sf_dir, "documents", "doc_id", "lang"), "doc_id", 10, "lang").select("lang", "doc_id")


_SETS = {
    "set_union": ("union", lambda a, b: a.union(b).distinct()),
    "set_union_all": ("union all", lambda a, b: a.union(b)),
    "set_intersect": ("intersect", lambda a, b: a.intersect(b)),
    "set_intersect_all": ("intersect all", lambda a, b: a.intersectAll(b)),
    "set_except": ("except", lambda a, b: a.subtract(b)),
    "set_except_all": ("except all", lambda a, b: a.exceptAll(b)),
}


def _set(op):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return op(table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")))

    return run


for _name, (_sql, _op) in _SETS.items():
    query(_name, f"select c_nationkey as k from customer {_sql} select s_nationkey as k from supplier")(_set(_op))


@query("dedup_exact", "select count(*) as n from (select distinct text from documents)")
def dedup_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents", "text").dropDuplicates().agg(F.count(F.lit(1)).alias("n"))


@query("dedup_keep_first", "select doc_id, lang from (select *, row_number() over (partition by text order by doc_id) as r from documents) where r = 1")
def dedup_keep_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.dedup_keep_first(table(spark, sf_dir, "documents", "text", "doc_id", "lang"), ["text"], ["doc_id"]).select("doc_id", "lang")
