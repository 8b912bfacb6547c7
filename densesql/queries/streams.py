"""Streaming queries run to the end of their input; the oracle is the batch form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.functions import text as T
from densesql.plans.staging import Staging
from densesql.queries import query
from densesql.sources.tables import table
from densesql.streaming import engine as E


def _events(spark: SparkSession, sf_dir: str, staging: Staging) -> DataFrame:
    return E.file_stream(spark, sf_dir, "events", staging, "ts")


def _text(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query(
    "stream_tumbling",
    """with w as (select time_bucket(interval 1 day, ts, timestamp '1970-01-01') as b, * from events)
    select strftime(b, '%Y-%m-%d %H:%M:%S') as start, count(*) as n, count_if(event_type = 'error') as errors, round(sum(value), 4) as total from w group by b""",
)
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    found = E.drain(E.tumbling(_events(spark, sf_dir, staging)), staging, "out", "complete")
    return found.select(_text("start").alias("start"), "n", "errors", F.round("total", 4).alias("total"))


@query(
    "stream_sliding",
    """with w as (select time_bucket(interval 1 hour, ts, timestamp '1970-01-01') - to_hours(i) as b, event_type from events, range(0, 6) t(i))
    select strftime(b, '%Y-%m-%d %H:%M:%S') as start, count(*) as n, round(avg(case when event_type = 'error' then 1.0 else 0.0 end), 6) as rate from w group by b""",
)
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    found = E.drain(E.sliding(_events(spark, sf_dir, staging)), staging, "out", "complete")
    return found.select(_text("start").alias("start"), "n", F.round("rate", 6).alias("rate"))


@query(
    "stream_session",
    """with p as (select user_id, ts, lag(ts) over (partition by user_id order by ts) as before from events),
    s as (select user_id, ts, sum(case when before is null or ts >= before + interval 30 minute then 1 else 0 end) over (partition by user_id order by ts rows unbounded preceding) as k from p)
    select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n from s group by user_id, k""",
)
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    found = E.drain(E.sessions(_events(spark, sf_dir, staging)), staging, "out", "complete")
    return found.select("user_id", _text("start").alias("start"), "n")


@query("stream_dedup", "select user_id, event_type from events group by user_id, event_type")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    return E.drain(E.dedup(_events(spark, sf_dir, staging), ["user_id", "event_type"]), staging, "out").select("user_id", "event_type")


@query(
    "stream_interval_join",
    "select v.event_id as view_id, p.event_id as purchase_id from events v join events p on v.user_id = p.user_id and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour where v.event_type = 'view' and p.event_type = 'purchase'",
)
def stream_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    events = E.file_stream(spark, sf_dir, "events", staging, "ts", parts=1)  # in order of time, so nothing is late
    return E.drain(E.interval_join(events.where("event_type = 'view'"), events.where("event_type = 'purchase'")), staging, "out")


@query("stream_static_join", "select event_id, mean from events join (select user_id, round(avg(value), 6) as mean from events group by user_id) m using (user_id) where event_type = 'purchase'")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    staging = Staging(spark, "stream")
    snapshot = table(spark, sf_dir, "events").groupBy("user_id").agg(F.round(F.avg("value"), 6).alias("mean"))
    joined = E.static_join(_events(spark, sf_dir, staging).where("event_type = 'purchase'"), snapshot, "user_id")
    return E.drain(joined.select("event_id", "mean"), staging, "out")


@query(
    "stream_running_advantage",
    """with r as (select user_id, value, row_number() over (partition by user_id order by ts, event_id) as i, count(*) over (partition by user_id) as k from events)
    select user_id as question_id, count(*) as n, round(avg(value), 8) as mean, round(stddev_pop(value), 5) as std from r where i <= 16 and k >= 16 group by user_id""",
)
def stream_running_advantage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Online reward statistics of each question's first sixteen rollouts."""
    staging = Staging(spark, "stream")
    events = E.file_stream(spark, sf_dir, "events", staging, "ts", parts=1)  # "first" needs arrival in order of time
    e = events.select(F.col("user_id").alias("question_id"), F.col("event_id").alias("rollout_id"), "ts", F.col("value").alias("total"))
    found = E.drain(E.running_advantages(e, 16), staging, "out")
    return found.select("question_id", "n", F.round("mean", 8).alias("mean"), F.round("std", 5).alias("std"))


@query("stream_admit_batches", "select distinct md5(text) as digest from documents where len(regexp_extract_all(lower(text), '[a-z0-9_]+')) between 30 and 2000")
def stream_admit_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A memory that grows by micro-batches: texts that pass the length rule and are not there yet."""
    staging = Staging(spark, "stream")
    docs = E.file_stream(spark, sf_dir, "documents", staging, "doc_id").select("doc_id", "text")

    def admit(batch: DataFrame, known: DataFrame | None, _: int) -> DataFrame:
        gated = batch.where(T.gate_length(T.tokens(F.col("text"))))
        first = gated.groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.min("doc_id").alias("doc_id"))
        return first if known is None else first.join(known.select("digest"), "digest", "left_anti")

    return E.admit_batches(docs, staging, admit).select("digest")


@query(
    "stream_late_rows",
    "with a as (select *, max(ts) over (order by event_id rows between unbounded preceding and 1 preceding) as newest from events) select event_id from a where ts < newest - interval 10 day",
)
def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows a ten-day watermark would drop if events arrived in id order."""
    return E.late_rows(table(spark, sf_dir, "events").withColumn("arrival", F.col("event_id")), "10 days").select("event_id")
