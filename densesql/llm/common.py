"""Shared pieces of the training-data operators."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator
from functools import wraps

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Characters between words: space and the controls from tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"

#: Bytes of an Arrow batch on its way to Python.
BATCH_BYTES = 4 << 20


def documents(spark: SparkSession, sf_dir: str, table: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def squeezed(text: Column, breaks: str = r"[\x20\x09-\x0D]+") -> Column:
    """The words of a text with one blank between them; null has none."""
    return F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), breaks, " "))


def word_count(text: Column, breaks: str = r"[\x20\x09-\x0D]+") -> Column:
    """Words of a text as a JVM expression."""
    words = squeezed(text, breaks)
    return F.when(words == "", F.lit(0)).otherwise(F.length(words) - F.length(F.translate(words, " ", "")) + 1).cast("long")


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """An Arrow function whose worker gives its free memory back at the end of a task.

    Workers are kept for later stages, where what they hold on to counts against the executor.
    """

    @wraps(run)
    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
            if trim is not None:
                trim(0)

    return task


def map_rows(df: DataFrame, columns: list[str], schema: str, make: Callable[[], Callable[..., Iterable[tuple]]], carry: tuple[str, ...] = ()) -> DataFrame:
    """One output row per input row, from a plain function over Arrow batches.

    ``make`` runs once in each task and returns a function from the batch's column lists
    to an iterable of output tuples, so that compiled patterns and tables are built once.
    ``carry`` columns go along untouched, named k0, k1 and so on before the others.
    """
    kinds = [df.schema[c].dataType.simpleString() for c in carry]
    full = ", ".join([*(f"k{n} {kind}" for n, kind in enumerate(kinds)), schema])
    new_type, out_type, n_in = arrow_schema(df.sparkSession, schema), arrow_schema(df.sparkSession, full), len(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            for piece in bounded(batch):
                rows = list(step(*[piece.column(k).to_pylist() for k in range(n_in)]))
                if rows:
                    cols = [pa.array(values, type=field.type) for values, field in zip(zip(*rows, strict=True), new_type, strict=True)]
                    kept = [piece.column(n_in + k).cast(out_type.field(k).type) for k in range(len(kinds))]
                    yield pa.RecordBatch.from_arrays([*kept, *cols], schema=out_type)

    small_batches(df.sparkSession)
    inputs = [*[F.col(f"`{c}`").alias(f"i{n}") for n, c in enumerate(columns)], *[F.col(f"`{c}`").alias(f"k{n}") for n, c in enumerate(carry)]]
    return df.select(*inputs).mapInArrow(trimmed(run), full)


def small_batches(spark: SparkSession) -> None:
    """Bound the bytes of an Arrow batch, whose buffers the JVM holds outside its heap (a runtime setting)."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if int(spark.conf.get(key).rstrip("b")) > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def numbered(docs: DataFrame, *needed: str) -> tuple[DataFrame, list[str]]:
    """``docs`` with its columns as c0, c1, ... beside copies of the needed ones, and the new names.

    Operators that return whole rows work on such a copy, so that no column of the caller
    can clash with one of theirs.
    """
    names = docs.columns
    own = docs.toDF(*[f"c{n}" for n in range(len(names))])
    return own.select("*", *[F.col(f"c{names.index(x)}").alias(x) for x in needed]), own.columns


def bounded(batch: pa.RecordBatch, max_bytes: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that a piece holds about ``max_bytes``, or one row if that is larger."""
    parts = max(1, -(-batch.nbytes // max_bytes))
    step = max(1, -(-batch.num_rows // parts))
    for k in range(0, batch.num_rows, step):
        yield batch.slice(k, step)


def arrow_schema(spark: SparkSession, ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))
