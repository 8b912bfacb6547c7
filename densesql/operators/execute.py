"""Running candidate SQL: guard, analyse, run once, digest, compare.

Only distinct (database, SQL) pairs reach the driver, in bounded chunks, because Spark
analyses statements there.  Results never leave the executors: each is reduced to a
digest that does not depend on row order or partitioning.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from itertools import islice
from threading import Timer
from uuid import uuid4

from pyspark.errors import PySparkException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densesql.operators.sqlast import ParseError, lex, parse
from densesql.plans.staging import Staging
from densesql.sources.tables import register_database

STATUS = "db_id string, sql string, status string, error_class string, n_cols int, n_rows long, h_a decimal(38,0), h_b decimal(38,0), h_order decimal(38,0)"
#: Distinct statements in flight on the driver at once, and threads that run them.
CHUNK, THREADS = 512, 8
#: Seconds that a statement may take, and rows that a result may have: beyond either it counts as failed.
TIMEOUT_S, MAX_ROWS = 300.0, 50_000_000

# Functions that reach beyond the tables.
FORBIDDEN = frozenset(
    """java_method reflect try_reflect input_file_name input_file_block_start input_file_block_length read_files current_user user
    session_user version spark_partition_id raise_error assert_true""".split()
)


def guard(sql: str) -> str | None:
    """Why a text must not run: anything but one query over named tables; None if it may.

    A text that our parser cannot read is left to Spark's, unless it does not begin like a
    query or holds a forbidden word or a table given by its path.
    """
    try:
        tokens = lex(sql)
    except ParseError:
        return "lexical"
    words = {v for k, v in tokens if k in ("word", "name")}
    if words & FORBIDDEN:
        return "forbidden_function"
    if any(k == "name" and re.search(r"[/:\\]", v) for k, v in tokens) or re.search(r"`[^`]*[/:\\][^`]*`", sql):
        return "path_table"
    if any(a == ("op", ".") and k == "name" and re.search(r"[/.]", v) for a, (k, v) in zip(tokens, tokens[1:], strict=False)):
        return "path_table"
    if not tokens or tokens[0][1] not in ("select", "with", "("):
        return "not_a_query"
    if ("op", ";") in tokens[:-1]:
        return "many_statements"
    try:
        parse(sql)
    except ParseError:
        if words & {"insert", "update", "delete", "drop", "create", "alter", "set", "cache", "load", "transform", "call"}:
            return "not_a_query"
    return None


def _cell(c: Column, kind: T.DataType) -> Column:
    """A cell as text that equal values share: doubles to nine significant digits, null marked."""
    if isinstance(kind, T.FloatType | T.DoubleType | T.DecimalType):
        x = c.cast("double")
        shown = F.when(F.isnan(x), "nan").when(x == 0, "0").otherwise(F.format_string("%.8e", x))
    elif isinstance(kind, T.TimestampType):
        shown = F.unix_micros(c).cast("string")
    elif isinstance(kind, T.ArrayType | T.MapType | T.StructType):
        shown = F.to_json(F.struct(c.alias("x")))
    else:
        shown = c.cast("string")
    return F.coalesce(F.concat(F.lit("v"), shown), F.lit("n"))


def digest(df: DataFrame, ordered: bool = False, sort_columns: bool = False) -> DataFrame:
    """One row (n_rows, h_a, h_b, h_order): two sums of differently seeded row hashes.

    Sums keep duplicates apart, unlike xor.  ``sort_columns`` sorts a row's cells first, so
    that column order does not matter.  ``ordered`` weighs hashes by row number; it sorts
    nothing and numbers the rows of the result as they come.
    """
    named = df.toDF(*[f"c{k}" for k in range(len(df.columns))])
    cells = [_cell(F.col(f.name), f.dataType) for f in named.schema.fields]
    row = [F.array_join(F.array_sort(F.array(*cells)), "\x1f")] if sort_columns else cells
    a, b = (F.xxhash64(F.lit(seed), *row).cast("decimal(38,0)") for seed in (1, 2))
    parts = named.select(a.alias("a"), b.alias("b"), F.monotonically_increasing_id().alias("at"))
    order = F.lit(None).cast("decimal(38,0)")
    if ordered:
        order = F.sum(F.xxhash64("a", "at").cast("decimal(38,0)"))
        parts = parts.coalesce(1).withColumn("at", F.monotonically_increasing_id())
    total = lambda c: F.coalesce(F.sum(c), F.lit(0).cast("decimal(38,0)")).cast("decimal(38,0)")
    return parts.agg(F.count(F.lit(1)).alias("n_rows"), total("a").alias("h_a"), total("b").alias("h_b"), order.cast("decimal(38,0)").alias("h_order"))


def _failure(e: Exception) -> tuple[str, str]:
    text = (e.getCondition() if isinstance(e, PySparkException) else None) or type(e).__name__
    kind = "parse" if "PARSE" in text else "runtime" if any(w in text for w in ("DIVIDE", "ARITHMETIC", "OVERFLOW", "CAST", "Py4J", "SparkException")) else "analyse"
    return kind, text


class _Clock:
    """Calls a function once after so many seconds unless cancelled; ``fired`` tells whether it did."""

    def __init__(self, seconds: float, action: Callable[[], None]):
        self.fired = False

        def fire() -> None:
            self.fired = True
            action()

        self._timer = Timer(seconds, fire)
        self._timer.daemon = True
        self._timer.start()

    def cancel(self) -> None:
        self._timer.cancel()


def _chunks(rows: Iterator, n: int) -> Iterable[list]:
    while chunk := list(islice(rows, n)):
        yield chunk


def run(
    spark: SparkSession, sf_dir: str, candidates: DataFrame, ordered: bool = False, sort_columns: bool = False, timeout_s: float = TIMEOUT_S, max_rows: int = MAX_ROWS,
) -> DataFrame:
    """(db_id, sql, status, error_class, n_cols, n_rows, h_a, h_b, h_order) for the distinct candidates.

    Status is ``runs``, ``parse``, ``analyse``, ``runtime`` or ``forbidden``.  Statements whose
    analysed plans are equal run once within a chunk.  A statement that takes longer than
    ``timeout_s`` is cancelled; of a result no more than ``max_rows + 1`` rows are digested, and
    a larger one fails.  Each chunk's digests are staged, so the driver holds one chunk only.
    """
    sessions: dict[str, SparkSession] = {}
    staging, paths = Staging(spark, "executed"), []
    distinct = candidates.select("db_id", "sql").where("sql is not null and db_id is not null").distinct()
    for chunk in _chunks(distinct.toLocalIterator(), CHUNK):
        rows = _run_chunk(spark, sf_dir, chunk, sessions, ordered, sort_columns, timeout_s, max_rows)
        staging.table(spark.createDataFrame(rows, STATUS).coalesce(1), f"chunk-{len(paths)}")
        paths.append(staging.path(f"chunk-{len(paths)}"))
    return spark.read.schema(STATUS).parquet(*paths) if paths else spark.createDataFrame([], STATUS)


#: What ``run_new`` has executed, by application and tables.
_RAN: dict[tuple[str, str], DataFrame] = {}


def run_new(spark: SparkSession, sf_dir: str, candidates: DataFrame) -> DataFrame:
    """``run`` that executes only what it has not yet executed on these tables in this session; it returns all of that."""
    key, wanted = (spark.sparkContext.applicationId, sf_dir), candidates.select("db_id", "sql")
    known = _RAN.get(key)
    found = run(spark, sf_dir, wanted if known is None else wanted.join(known.select("db_id", "sql"), ["db_id", "sql"], "left_anti"))
    _RAN[key] = found if known is None else known.unionByName(found)
    return _RAN[key]


def _run_chunk(spark: SparkSession, sf_dir: str, chunk: list, sessions: dict, ordered: bool, sort_columns: bool, timeout_s: float, max_rows: int) -> list[tuple]:
    """The digests of one chunk of (db_id, sql)."""
    out: list[tuple] = []
    plans: dict[tuple, list] = {}
    for db, sql in chunk:
        why = guard(sql)
        if why:
            kind = "forbidden" if why in ("forbidden_function", "path_table", "many_statements") else "parse"
            out.append((db, sql, kind, why, None, None, None, None, None))
            continue
        try:
            if db not in sessions:
                sessions[db] = register_database(spark, sf_dir, db)
            df = sessions[db].sql(sql)
            group = plans.setdefault((db, df.semanticHash(), len(df.columns)), [])
            same = next((g for g in group if g[0].sameSemantics(df)), None)
            if same:
                same[1].append(sql)
            else:
                group.append((df, [sql]))
        except Exception as e:  # noqa: BLE001 - candidate SQL may fail in any way
            kind, text = _failure(e)
            out.append((db, sql, kind, text, None, None, None, None, None))
    context = spark.sparkContext

    def one(item: tuple) -> list[tuple]:
        db, df, texts = item
        width, tag = len(df.columns), f"candidate-{uuid4().hex}"
        fail = lambda kind, text: [(db, s, kind, text, width, None, None, None, None) for s in texts]
        context.addJobTag(tag)
        clock = _Clock(timeout_s, lambda: context.cancelJobsWithTag(tag))
        try:
            n, a, b, o = digest(df.limit(max_rows + 1), ordered, sort_columns).first()
            if n > max_rows:
                return fail("runtime", "too_many_rows")
            return [(db, s, "runs", None, width, n, a, b, o) for s in texts]
        except Exception as e:  # noqa: BLE001
            if clock.fired:
                return fail("runtime", "timeout")
            kind, text = _failure(e)
            return fail("runtime" if kind == "analyse" else kind, text)
        finally:
            clock.cancel()
            context.removeJobTag(tag)

    with ThreadPoolExecutor(THREADS) as pool:
        for rows in pool.map(one, [(key[0], df, texts) for key, group in plans.items() for df, texts in group]):
            out += rows
    return out


def matches(a: str = "p", b: str = "g", mode: str = "bag") -> Column:
    """Whether two digests (column prefixes) say the same result: ``bag``, or ``ordered`` as well."""
    same = (F.col(f"{a}.n_cols") == F.col(f"{b}.n_cols")) & (F.col(f"{a}.n_rows") == F.col(f"{b}.n_rows"))
    same = same & (F.col(f"{a}.h_a") == F.col(f"{b}.h_a")) & (F.col(f"{a}.h_b") == F.col(f"{b}.h_b"))
    return same & (F.col(f"{a}.h_order") == F.col(f"{b}.h_order")) if mode == "ordered" else same


def compare(a: DataFrame, b: DataFrame, mode: str = "bag") -> bool:
    """Exact comparison of two results: ``bag``, ``set``, ``ordered`` or ``bag_colperm``."""
    if len(a.columns) != len(b.columns):
        return False
    if mode in ("ordered", "bag_colperm"):
        x, y = (digest(df, mode == "ordered", mode == "bag_colperm").first() for df in (a, b))
        return tuple(x) == tuple(y)
    b = b.toDF(*a.columns)
    if mode == "set":
        return a.subtract(b).isEmpty() and b.subtract(a).isEmpty()
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def judge(spark: SparkSession, sf_dir: str, parsed: DataFrame, questions: DataFrame, executed: DataFrame | None = None) -> DataFrame:
    """``parsed`` rollouts with status, error_class, result (digest text) and correct."""
    gold = questions.select("question_id", "gold_sql", "db_id")
    if executed is None:
        texts = parsed.select("db_id", "sql").union(gold.select("db_id", F.col("gold_sql").alias("sql")))
        executed = run(spark, sf_dir, texts)
    key = F.concat_ws(":", "n_cols", "n_rows", "h_a", "h_b")
    known = executed.select("db_id", "sql", "status", "error_class", "n_rows", F.when(F.col("status") == "runs", key).alias("result"))
    wanted = gold.join(known.select("db_id", F.col("sql").alias("gold_sql"), F.col("result").alias("gold_result"), F.col("n_rows").alias("gold_rows")), ["db_id", "gold_sql"])
    joined = parsed.join(known, ["db_id", "sql"], "left").join(wanted.select("question_id", "gold_result", "gold_rows"), "question_id", "left")
    return joined.withColumns(
        {"status": F.coalesce("status", F.lit("parse")), "correct": F.coalesce(F.col("result") == F.col("gold_result"), F.lit(False))}
    )
