"""Token counts as delta-maintained rollups.

A change is a signed number of documents and tokens for a key (source, language,
tokenizer version): an insert adds, a delete subtracts what was counted, a revision
adds the difference.  A batch is summed by key before it is written, so totals are
plain sums over committed batches and never need the texts again.

Commits are idempotent: a batch's rows are written below its own name and count only
once its marker stands; a batch that is already marked is left alone, and one that
failed half-way is written anew.  ``compact`` folds committed batches into one.

Defined results: null source or language is a key of its own; a null text counts no
words; repeated rows each count; keys whose documents sum to zero leave the totals; an
empty batch commits and changes nothing; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents, word_count
from densesql.plans.staging import Staging, delete_path, path_exists

KEYS = ["source", "lang", "tokenizer"]
SUMS = ["n_docs", "n_tokens"]
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long"
#: What stands between the words of the second tokenizer: ASCII other than letters and digits.
RUN_BREAK = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


class DeltaRollup:
    """Additive totals in a shared folder, changed by named batches of signed rows."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root

    def _batch(self, batch: str) -> str:
        return f"{self.root}/batch={batch}"

    def committed(self, batch: str) -> bool:
        return path_exists(self.spark, f"{self._batch(batch)}/_SUCCESS")

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Add a batch of signed changes; False where it had been committed before."""
        if self.committed(batch):
            return False
        summed = changes.groupBy(*KEYS).agg(*[F.sum(c).cast("long").alias(c) for c in SUMS])
        summed.write.mode("overwrite").parquet(self._batch(batch))
        return True

    def _names(self) -> list[str]:
        if not path_exists(self.spark, self.root):
            return []
        root = self.spark._jvm.org.apache.hadoop.fs.Path(self.root)
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        names = [s.getPath().getName() for s in fs.listStatus(root) if s.getPath().getName().startswith("batch=")]
        return sorted(n.removeprefix("batch=") for n in names if self.committed(n.removeprefix("batch=")))

    def totals(self) -> DataFrame:
        """(source, lang, tokenizer, n_docs, n_tokens) over all committed batches."""
        paths = [self._batch(b) for b in self._names()]
        rows = self.spark.read.schema(SCHEMA).parquet(*paths) if paths else self.spark.createDataFrame([], SCHEMA)
        summed = rows.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in SUMS])
        return summed.where("n_docs != 0 or n_tokens != 0")

    def compact(self, batch: str) -> None:
        """Fold every committed batch into one of the given new name.

        Readers between the two steps would count twice, so compaction needs a single writer
        and no reader; the folded names are remembered by empty marked batches.
        """
        names = self._names()
        self.totals().coalesce(1).write.mode("overwrite").parquet(self._batch(batch))
        for name in names:
            delete_path(self.spark, self._batch(name))
            self.spark.createDataFrame([], SCHEMA).write.parquet(self._batch(name))


def signed(rows: DataFrame, tokenizer: str, tokens: Column, docs: int) -> DataFrame:
    """Changes with the same sign for each row: ``docs`` is 1, -1 or (for a revision) 0."""
    return rows.select("source", "lang", F.lit(tokenizer).alias("tokenizer"), F.lit(docs).cast("long").alias("n_docs"), tokens.cast("long").alias("n_tokens"))


def count_corpus(docs: DataFrame, root: str | None = None) -> DataFrame:
    """Run a corpus through insert, revision, second tokenizer and deletion, with replays.

    Every document is inserted with a provisional count of a quarter of its characters,
    revised to its words, inserted again under the second tokenizer, and deleted from
    both if an earlier row has the same text.
    """
    staging = Staging(docs.sparkSession, "rollup")
    text = F.coalesce("text", F.lit(""))
    counted = docs.select(
        "doc_id", "source", "lang", F.md5(text.cast("binary")).alias("body"),
        F.floor(F.length(text) / 4).alias("estimate"), word_count(F.col("text")).alias("words"), word_count(F.col("text"), RUN_BREAK).alias("runs"),
    )
    counted = staging.table(counted, "counted", row_id="row_id")
    rank = F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col("row_id"))
    first = counted.groupBy("body").agg(F.min(rank).alias("first")).select(F.col("first.row_id").alias("row_id"))
    later = counted.join(first, "row_id", "left_anti")
    rollup = DeltaRollup(docs.sparkSession, root or staging.path("totals"))
    insert = signed(counted, "words-1", F.col("estimate"), 1)
    revise = signed(counted, "words-1", F.col("words") - F.col("estimate"), 0)
    second = signed(counted, "runs-2", F.col("runs"), 1)
    delete = signed(later, "words-1", -F.col("words"), -1).union(signed(later, "runs-2", -F.col("runs"), -1))
    for name, changes in (("1-insert", insert), ("2-revise", revise), ("2-revise", revise), ("3-second", second), ("4-delete", delete), ("1-insert", insert)):
        rollup.commit(name, changes)
    return rollup.totals()


def op7_token_rollups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_corpus(documents(spark, sf_dir))


ORACLE = r"""
with d as (
    select source, lang, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as words,
        len(regexp_extract_all(coalesce(text, ''), '[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+')) as runs,
        row_number() over (partition by coalesce(text, '') order by doc_id nulls last) as copy
    from documents
), k as (select * from d where copy = 1)
select source, lang, 'words-1' as tokenizer, count(*) as n_docs, cast(sum(words) as bigint) as n_tokens from k group by source, lang
union all
select source, lang, 'runs-2' as tokenizer, count(*) as n_docs, cast(sum(runs) as bigint) as n_tokens from k group by source, lang
"""
