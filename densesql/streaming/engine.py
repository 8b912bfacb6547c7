"""Streaming forms of the measures and of the memory's upkeep.

Every query reads files as a stream and is run to the end of what is there
(``availableNow``) into a staged table, so that it can be compared with its batch form.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densesql.plans.staging import Staging

WATERMARK = "2 hours"
#: Arrival numbers of a range in which late rows are looked for.
ARRIVALS = 1 << 20


def file_stream(spark: SparkSession, sf_dir: str, name: str, staging: Staging, order: str | None = None, parts: int = 3, per_trigger: int = 1) -> DataFrame:
    """A given table as a stream of ``parts`` files, in the order of a column where one is named.

    The source takes files by their times, which the tasks of one write leave to chance, so
    the times are set in the order of the parts, a second apart.
    """
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema if f.dataType.typeName() == "timestamp_ntz"})
    df = df.repartitionByRange(parts, order).sortWithinPartitions(order) if order else df.repartition(parts)
    df.write.mode("overwrite").parquet(staging.path(f"in-{name}"))
    _time_in_order(spark, staging.path(f"in-{name}"))
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", per_trigger).parquet(staging.path(f"in-{name}"))


def _time_in_order(spark: SparkSession, folder: str) -> None:
    """Give the part files of a folder ascending times; names ascend with the partition that wrote them."""
    root = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    files = sorted((s.getPath() for s in fs.listStatus(root) if s.getPath().getName().startswith("part-")), key=lambda p: p.getName())
    newest = max((fs.getFileStatus(p).getModificationTime() for p in files), default=0)
    for k, path in enumerate(files):
        fs.setTimes(path, newest - 1000 * (len(files) - k), -1)


def drain(stream: DataFrame, staging: Staging, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over everything that is there and read back what it wrote."""
    writer = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", staging.path(f"{name}-checkpoint"))
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", staging.path(name)).start().awaitTermination()
    else:

        def replace(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(staging.path(name))

        writer.outputMode("complete").foreachBatch(replace).start().awaitTermination()
    return staging.spark.read.schema(stream.schema).parquet(staging.path(name))


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    """(start, n, errors, total): counts and rewards by time bucket."""
    w = events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", width))
    return w.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("event_type") == "error").alias("errors"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "n", "errors", "total")


def sliding(events: DataFrame, width: str = "6 hours", slide: str = "1 hour") -> DataFrame:
    """(start, n, rate): the moving error rate."""
    w = events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", width, slide))
    return w.agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("event_type") == "error").cast("double")).alias("rate")).select(F.col("window.start").alias("start"), "n", "rate")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n): bursts of a user."""
    w = events.withWatermark("ts", WATERMARK).groupBy("user_id", F.session_window("ts", gap))
    return w.agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def dedup(events: DataFrame, by: list[str]) -> DataFrame:
    """The first row of each key among those whose times lie within the watermark."""
    return events.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(by)


def interval_join(views: DataFrame, purchases: DataFrame, width: str = "1 hour") -> DataFrame:
    """Purchases within ``width`` of a view of the same user, both sides streams."""
    a = views.select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("t0")).withWatermark("t0", WATERMARK)
    b = purchases.select(F.col("user_id").alias("w"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("t1")).withWatermark("t1", WATERMARK)
    return a.join(b, F.expr(f"u = w and t1 >= t0 and t1 <= t0 + interval {width}")).select("view_id", "purchase_id")


def static_join(events: DataFrame, snapshot: DataFrame, on: str) -> DataFrame:
    """A stream against a snapshot of a table, which is read anew for each batch."""
    return events.join(snapshot, on)


def running_advantages(events: DataFrame, group: int) -> DataFrame:
    """(question_id, n, mean, std): a group's reward statistics, emitted once ``group`` rewards are there.

    State is three numbers a question, kept until the group is full.
    """
    out = T.StructType([T.StructField("question_id", T.LongType()), T.StructField("n", T.LongType()), T.StructField("mean", T.DoubleType()), T.StructField("std", T.DoubleType())])
    state = T.StructType([T.StructField("n", T.LongType()), T.StructField("s", T.DoubleType()), T.StructField("q", T.DoubleType())])

    def step(key: tuple, batches: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:
        n, s, q = held.get if held.exists else (0, 0.0, 0.0)
        for pdf in batches:
            for x in pdf.sort_values(["ts", "rollout_id"])["total"]:
                if n < group:
                    n, s, q = n + 1, s + x, q + x * x
                    if n == group:
                        mean = s / n
                        yield pd.DataFrame({"question_id": [key[0]], "n": [n], "mean": [mean], "std": [max(0.0, q / n - mean * mean) ** 0.5]})
        held.update((n, s, q))

    return events.groupBy("question_id").applyInPandasWithState(step, out, state, "append", "NoTimeout")


def admit_batches(stream: DataFrame, staging: Staging, admit: Callable[[DataFrame, DataFrame | None, int], DataFrame], name: str = "memory") -> DataFrame:
    """Grow a memory by micro-batches: each batch's accepted rows go below its own id, so a replay changes nothing."""

    def run(batch: DataFrame, batch_id: int) -> None:
        from densesql.plans.staging import path_exists

        spark = batch.sparkSession
        known = None
        older = [f"{staging.path(name)}/batch_id={k}" for k in range(batch_id) if path_exists(spark, f"{staging.path(name)}/batch_id={k}")]
        if older:
            known = spark.read.parquet(*older)
        admit(batch, known, batch_id).write.mode("overwrite").parquet(f"{staging.path(name)}/batch_id={batch_id}")

    writer = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", staging.path(f"{name}-checkpoint"))
    writer.foreachBatch(run).start().awaitTermination()
    return staging.spark.read.option("basePath", staging.path(name)).parquet(staging.path(name))


def late_rows(events: DataFrame, delay: str) -> DataFrame:
    """Rows later than the watermark would allow, from a batch in arrival order: (event_id, ts, newest).

    Arrival is cut into ranges of ``ARRIVALS`` ids; the newest time before a range comes from a
    small window over the ranges' maxima, so no task sees more than one range or all maxima.
    """
    cut = events.withColumn("_cut", F.floor(F.col("arrival") / ARRIVALS))
    maxima = cut.groupBy("_cut").agg(F.max("ts").alias("_top"))
    ahead = Window.orderBy("_cut").rowsBetween(Window.unboundedPreceding, -1)
    tops = maxima.select(F.col("_cut").alias("_c"), F.max("_top").over(ahead).alias("_before"))
    within = F.max("ts").over(Window.partitionBy("_cut").orderBy("arrival").rowsBetween(Window.unboundedPreceding, -1))
    ranked = cut.repartition("_cut").withColumn("_within", within)
    newest = ranked.join(tops, F.col("_cut") == F.col("_c")).withColumn("newest", F.greatest("_within", "_before"))
    return newest.where(F.expr(f"ts < newest - interval {delay}")).select("event_id", "ts", "newest")
