"""The given tables, their logical databases, and files in and out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)

#: Logical databases: their tables and (table, column, table, column) references.
DATABASES: dict[str, tuple[tuple[str, ...], tuple[tuple[str, str, str, str], ...]]] = {
    "sales": (
        ("customer", "orders", "lineitem"),
        (("orders", "o_custkey", "customer", "c_custkey"), ("lineitem", "l_orderkey", "orders", "o_orderkey")),
    ),
    "supply": (
        ("supplier", "part", "lineitem", "nation"),
        (
            ("lineitem", "l_partkey", "part", "p_partkey"),
            ("lineitem", "l_suppkey", "supplier", "s_suppkey"),
            ("supplier", "s_nationkey", "nation", "n_nationkey"),
        ),
    ),
    "geo": (
        ("region", "nation", "customer", "supplier"),
        (
            ("nation", "n_regionkey", "region", "r_regionkey"),
            ("customer", "c_nationkey", "nation", "n_nationkey"),
            ("supplier", "s_nationkey", "nation", "n_nationkey"),
        ),
    ),
    "clicks": (("events",), ()),
    "docs": (("documents", "labels", "benchmark", "pages"), (("labels", "doc_id", "documents", "doc_id"),)),
    "chat": (("conversations",), ()),
    "vectors": (("embeddings",), ()),
}


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> dict[str, DataFrame]:
    """Register the tables as temporary views and return them."""
    found = {n: table(spark, sf_dir, n) for n in names}
    for n, df in found.items():
        df.createOrReplaceTempView(n)
    return found


def register_database(spark: SparkSession, sf_dir: str, db_id: str) -> SparkSession:
    """A new session in which only the database's tables are visible."""
    own = spark.newSession()
    for n in DATABASES[db_id][0]:
        table(own, sf_dir, n).createOrReplaceTempView(n)
    return own


def schema_columns(spark: SparkSession, sf_dir: str, db_ids: tuple[str, ...] = tuple(DATABASES)) -> DataFrame:
    """(db_id, table_name, column_name, data_type, ordinal, is_key): the catalogue, from file footers."""
    rows = []
    schemas = {n: table(spark, sf_dir, n).schema for db in db_ids for n in DATABASES[db][0]}
    for db in db_ids:
        keys = {(a, b) for a, b, _, _ in DATABASES[db][1]} | {(c, d) for _, _, c, d in DATABASES[db][1]}
        for n in DATABASES[db][0]:
            for k, f in enumerate(schemas[n].fields):
                rows.append((db, n, f.name, f.dataType.simpleString(), k, (n, f.name) in keys))
    return spark.createDataFrame(rows, "db_id string, table_name string, column_name string, data_type string, ordinal int, is_key boolean")


def schema_references(spark: SparkSession) -> DataFrame:
    """(db_id, table_name, column_name, ref_table, ref_column)."""
    rows = [(db, *ref) for db, (_, refs) in DATABASES.items() for ref in refs]
    return spark.createDataFrame(rows, "db_id string, table_name string, column_name string, ref_table string, ref_column string")


ROLLOUT = "question_id long, rollout_id int, db_id string, tier string, temperature double, step int, completion string"


def read_rollouts(spark: SparkSession, path: str, fmt: str = "json", schema: str = ROLLOUT) -> DataFrame:
    """Rollouts from JSON lines (malformed lines kept in ``_corrupt``), CSV, ORC or Parquet."""
    if fmt == "json":
        kept = StructType.fromDDL(schema + ", _corrupt string")
        return spark.read.schema(kept).option("columnNameOfCorruptRecord", "_corrupt").json(path)
    if fmt == "csv":
        return spark.read.schema(schema).option("header", True).option("multiLine", True).option("escape", '"').csv(path)
    return spark.read.schema(schema).format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), sort_by: tuple[str, ...] = ()) -> None:
    """Write files, clustered by the partition columns so that each value has few files."""
    out = df.repartition(*partition_by) if partition_by else df
    out = out.sortWithinPartitions(*sort_by) if sort_by else out
    writer = out.write.mode("overwrite").format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True).option("escape", '"')
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def memory_from_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(entry_id, db_id, embedding): the vectors as a memory whose databases are their labels."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("entry_id"), F.col("label").cast("string").alias("db_id"), "embedding")
