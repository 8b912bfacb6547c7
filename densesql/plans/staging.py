"""Tables that cut lineage, kept in the folder that all executors share.

A staged table is an ordinary Parquet table below ``spark.checkpoint.dir``.  It
survives the loss of any executor, is compressed and column-pruned on every later
read, and its rows keep their order and grouping by file, which a recomputed plan
does not promise.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from functools import wraps
from threading import get_ident, local

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The runtime setting by which an execution's shuffle files end with it.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

#: How staged tables are written: a writer holds a row group in memory until it is full.
FORMAT = {"compression": "zstd", "parquet.block.size": str(32 << 20)}

_LOCAL_ROOT: list[str] = []
_LIVE: set[Staging] = set()
#: The running steps' lists of what they have staged, by thread.
_OPENED = local()


def shared_root(spark: SparkSession) -> str:
    """The shared folder: ``spark.checkpoint.dir`` where set, else (local mode only) a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _LOCAL_ROOT:
        _LOCAL_ROOT.append(tempfile.mkdtemp(prefix="staged-"))
    return f"file://{_LOCAL_ROOT[0]}"


def delete_path(spark: SparkSession, path: str) -> None:
    """Delete a file or folder through the Hadoop file system that owns it."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def path_exists(spark: SparkSession, path: str) -> bool:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return bool(target.getFileSystem(spark._jsc.hadoopConfiguration()).exists(target))


@contextmanager
def shuffles_released(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the executions inside go when each ends: what they wrote is in the shared folder by then."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


class Staging:
    """One operator run's staged tables, below one folder that ``release`` deletes.

    Whatever the returned DataFrame still reads must stay until it has been used, so
    only tables known to be superseded are dropped early; the rest goes at exit.
    """

    def __init__(self, spark: SparkSession, purpose: str):
        self.spark = spark
        self.root = f"{shared_root(spark)}/{purpose}-{uuid.uuid4().hex}"
        _LIVE.add(self)
        for opened in getattr(_OPENED, "lists", []):
            opened.append(self)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def table(self, df: DataFrame, name: str, row_id: str | None = None) -> DataFrame:
        """Write ``df`` once and return a reader of it; ``row_id`` adds a unique long per row."""
        if row_id:
            df = df.withColumn(row_id, F.monotonically_increasing_id())
        with shuffles_released(self.spark):
            df.write.mode("overwrite").options(**FORMAT).parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, name: str) -> None:
        delete_path(self.spark, self.path(name))

    def release(self) -> None:
        delete_path(self.spark, self.root)
        _LIVE.discard(self)


class StepChain:
    """Steps whose results are each written before the next step begins.

    What a step staged has been read once the next one begins, and is deleted then.  Only
    tables of the same chain in the same thread are touched.
    """

    def __init__(self):
        self.earlier: dict[int, list[Staging]] = {}

    def step(self, function: Callable) -> Callable:
        @wraps(function)
        def run(*args):
            me = get_ident()
            for staging in self.earlier.pop(me, []):
                staging.release()
            opened: list[Staging] = []
            _OPENED.lists = [*getattr(_OPENED, "lists", []), opened]
            try:
                return function(*args)
            finally:
                _OPENED.lists = _OPENED.lists[:-1]
                self.earlier[me] = opened

        return run


@atexit.register
def _release_all() -> None:
    for staging in list(_LIVE):
        try:
            staging.release()
        except Exception:  # the session has already ended; nothing is left to delete with
            return
