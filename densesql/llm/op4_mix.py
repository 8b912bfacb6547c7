"""Mixing sources to target weights, to the word.

Targets share a total by weight and stop at a multiple of their source's size; what is
left over goes to the other sources by weight.  With sources ordered by size per
weight the stopped ones come first, so one pass of running sums finds all targets.

Every document gets a hash-random key.  A source's rows are range-cut and sorted by
it, prefix sums of word counts run over the ranges and within each, and the source is
cut at its exact budget: whole epochs first, then the documents before the cut, then
the part of one document that completes it.  All of it is DataFrame functions.

Defined results: a null or blank text has size 0 and takes nothing; a null source is a
source of its own, last in order; rows with equal doc_id and text are interchangeable,
repeated rows each count; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.llm.common import documents, squeezed, word_count
from densesql.plans.ranking import prefix_within_groups
from densesql.plans.staging import Staging

#: Weights go round by the source's place; a target stops at so many times the source's size.
WEIGHTS, MOST_EPOCHS = (1, 2, 3), 3


def _group(source: Column) -> Column:
    """A key that is never null: nulls sort after every source."""
    return F.when(source.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), source))


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_EPOCHS, share: float = 1.0) -> DataFrame:
    """(grp, source_size, target) from (grp, source_size): one row a source.

    Its windows run over all sources in one task: they grow with the number of sources, not of documents.
    """
    everything = Window.partitionBy()
    place = F.row_number().over(Window.orderBy("grp")) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int")).cast("long")
    by_room = Window.orderBy(F.col("source_size") / F.col("weight"), "grp")
    weighed = sizes.withColumn("weight", weight).withColumns(
        {
            "all": F.sum("source_size").over(everything) * F.lit(share),
            "stopped": F.coalesce(F.sum(F.col("source_size") * most).over(by_room.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)),
            "open": F.sum("weight").over(by_room.rowsBetween(0, Window.unboundedFollowing)),
        }
    )
    offered = (F.col("all") - F.col("stopped")) / F.col("open")
    tried = weighed.withColumn("offered", offered).withColumn("fits", F.col("offered") * F.col("weight") <= F.col("source_size") * most)
    whole = by_room.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    chosen = F.first(F.when(F.col("fits"), F.struct("all", "stopped", "open")), ignorenulls=True).over(whole)
    settled = tried.withColumns({"chosen": chosen, "past": F.max(F.col("fits")).over(by_room)})
    open_target = (F.col("chosen.all") - F.col("chosen.stopped")) * F.col("weight") / F.col("chosen.open")
    return settled.select("grp", "source_size", F.when(F.col("past"), open_target).otherwise(F.col("source_size") * most).cast("double").alias("target"))


def sized(docs: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, grp, size, uniform, key): what the mix needs of each document."""
    key = F.md5(F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.md5(F.coalesce("text", F.lit("")).cast("binary"))).cast("binary"))
    plain = docs.select("doc_id", _group(F.col("source")).alias("grp"), word_count(F.col("text")).alias("size"), key.alias("key"), *keep)
    return plain.withColumn("uniform", F.shiftright(F.conv(F.substring("key", 1, 8), 16, 10).cast("long"), 1))


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_EPOCHS, share: float = 1.0, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, key, size, source_size, target, taken, *keep) for every document."""
    staging = Staging(docs.sparkSession, "mix")
    rows = staging.table(sized(docs, keep), "sized")
    targets = staging.table(source_targets(rows.groupBy("grp").agg(F.sum("size").alias("source_size")), weights, most, share), "targets")
    ranked = prefix_within_groups(rows, staging, "grp", "uniform", ["key", "size"], "size", "words_before", "place")
    budget = F.round("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0)
    rest = budget - epochs * F.col("source_size")
    extra = F.least(F.greatest(rest - F.col("words_before"), F.lit(0)), F.col("size"))
    joined = ranked.join(targets.withColumnRenamed("grp", "tgrp"), F.col("grp") == F.col("tgrp"))
    return joined.select("doc_id", "key", "size", "source_size", "target", (epochs * F.col("size") + extra).cast("long").alias("taken"), *keep)


def mixed_rows(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_EPOCHS, share: float = 1.0) -> DataFrame:
    """The rows of the mix, with the columns of ``docs``: one copy for each epoch that takes the row.

    The copy at a source's cut holds the first words up to the budget, one blank between
    them, and its number of characters; everything else is unchanged.
    """
    staging = Staging(docs.sparkSession, "mixed")
    names = docs.columns
    own = docs.toDF(*[f"c{n}" for n in range(len(names))])
    column = {x: f"c{names.index(x)}" for x in names}
    needed = own.select("*", *[F.col(column[x]).alias(x) for x in ("doc_id", "text", "source")])
    rows = staging.table(needed, "rows", row_id="row_id")
    taken = mix(rows, weights, most, share, ("row_id",)).where("taken > 0").select("row_id", "size", "taken")
    copies = F.ceil(F.col("taken") / F.col("size")).cast("int")
    each = rows.join(taken, "row_id").withColumn("copy", F.explode(F.sequence(F.lit(1), copies)))
    left = F.least(F.col("size"), F.col("taken") - (F.col("copy") - 1) * F.col("size"))
    begun = F.call_function("substring_index", squeezed(F.col("text")), F.lit(" "), left.cast("int"))
    text = F.when(left == F.col("size"), F.col("text")).otherwise(begun)
    cut = each.withColumn("cut", text)
    shown = {column["text"]: F.col("cut")}
    if "n_chars" in column:
        kind = docs.schema["n_chars"].dataType
        shown[column["n_chars"]] = F.when(left == F.col("size"), F.col(column["n_chars"])).otherwise(F.length("cut").cast(kind))
    return cut.withColumns(shown).select(*own.columns).toDF(*names)


def op4_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
with d as (
    select doc_id, source, md5(concat(coalesce(cast(doc_id as varchar), '-'), ':', md5(coalesce(text, '')))) as key,
        len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as size
    from documents
), s as (
    select source, cast(sum(size) as bigint) as source_size, row_number() over (order by source nulls last) - 1 as place
    from d group by source
), w as (
    select *, place % 3 + 1 as weight, sum(source_size) over () as everything from s
), t as (
    select a.source, a.source_size, a.weight, any_value(a.everything) as everything,
        coalesce(sum(b.source_size * 3) filter (b.source_size * a.weight < a.source_size * b.weight), 0) as stopped,
        sum(b.weight) filter (b.source_size * a.weight >= a.source_size * b.weight) as open
    from w a cross join w b group by 1, 2, 3
), l as (
    select (everything - stopped) as words, open from t
    where (everything - stopped) * weight <= source_size * 3 * open
    order by source_size / weight limit 1
), g as (
    select source, source_size, cast(case when l.words * weight <= source_size * 3 * l.open
        then cast(l.words * weight as double) / l.open else source_size * 3 end as double) as target from t, l
), p as (
    select d.doc_id, d.size, g.source_size, g.target, cast(round(g.target) as bigint) as budget,
        coalesce(sum(d.size) over (partition by d.source order by d.key, d.size rows between unbounded preceding and 1 preceding), 0) as ahead
    from d join g on d.source is not distinct from g.source
)
select doc_id, cast(size as bigint) as size, source_size, target,
    cast(case when source_size > 0 then (budget // source_size) * size
        + least(greatest(budget % source_size - ahead, 0), size) else 0 end as bigint) as taken
from p
"""
