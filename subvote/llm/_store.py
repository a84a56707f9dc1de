"""Lineage cuts in the shared folder, and small helpers for plans that use them."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_own: dict[str, str] = {}
#: Runtime switch of Spark that drops the shuffle files of a finished execution.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Rows that go to a Python worker at once; texts are long, so fewer than Spark's default.
_BATCH, _BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", "1000"


def whole_row() -> Column:
    """All columns of a table as one, so that no name of theirs meets one of an operator's plan."""
    return F.struct("*").alias("row")


def text_tag(text: Column) -> Column:
    """Tells rows of one id apart by their text: 64 bits of its md5 digest."""
    return F.xxhash64(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where it is unset (tests)."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder shared by driver and executors")
    return "file://" + _own.setdefault("dir", tempfile.mkdtemp(prefix="subvote-"))


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@contextmanager
def _settings(spark: SparkSession, **extra: str) -> Iterator[None]:
    """Runtime settings of one write, put back afterwards."""
    wanted = {_CLEAN: "true", _BATCH: _BATCH_ROWS} | {k.replace("_", "."): v for k, v in extra.items()}
    before = {key: spark.conf.get(key, None) for key in wanted}
    try:
        for key, value in wanted.items():
            spark.conf.set(key, value)
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def materialize(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Write `df` as Parquet in the shared folder and read it back: the lineage ends there.

    The shuffle files behind it are dropped as soon as the table is written.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    with _settings(spark):
        df.write.options(**options).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._subvote_path = path
    return out


def write_run(df: DataFrame, path: str, keys: list[str], buckets: int) -> DataFrame:
    """Write `df`, an aggregation by `keys`, as an immutable run: bucketed and sorted by them.

    The aggregation's own exchange has as many partitions as the run has buckets, so every
    bucket is one sorted file and no further shuffle is needed.
    """
    with _settings(df.sparkSession, spark_sql_shuffle_partitions=str(buckets)):
        table = f"run_{uuid.uuid4().hex}"
        df.write.format("parquet").bucketBy(buckets, *keys).sortBy(*keys).option("path", path).saveAsTable(table)
        df.sparkSession.sql(f"DROP TABLE {table}")  # the files stay
    return open_run(df.sparkSession, path, df.schema.simpleString()[7:-1], keys, buckets)


def open_run(spark: SparkSession, path: str, schema: str, keys: list[str], buckets: int) -> DataFrame:
    """A run that is there, as a table whose buckets and order the planner knows."""
    table = f"run_{uuid.uuid4().hex}"
    columns, by = ", ".join(re.sub(r"^(\w+):", r"`\1` ", c) for c in _fields(schema)), ", ".join(keys)
    where = path.replace("'", "\\'")
    spark.sql(f"CREATE TABLE {table} ({columns}) USING parquet CLUSTERED BY ({by}) SORTED BY ({by}) INTO {buckets} BUCKETS LOCATION '{where}'")
    out = spark.table(table)
    out._subvote_path, out._subvote_table = path, table
    return out


def _fields(schema: str) -> list[str]:
    """Top-level fields of a schema string."""
    out, depth = [""], 0
    for c in schema:
        depth += (c == "<") - (c == ">")
        if c == "," and not depth:
            out.append("")
        else:
            out[-1] += c
    return out


#: Setting that lets a scan of one file per bucket report its order.
SORTED_SCAN = {"spark_sql_legacy_bucketedTableScan_outputOrdering": "true"}


def merge_joined(df: DataFrame, name: str) -> DataFrame:
    """`materialize` for plans over runs: joins on their keys neither shuffle nor sort them."""
    with _settings(df.sparkSession, **SORTED_SCAN):
        return materialize(df, name)


def discard(df: DataFrame | None) -> None:
    """Delete a table made here that no later plan reads; anything else is left alone."""
    if not hasattr(df, "_subvote_path"):
        return
    spark = df.sparkSession
    if hasattr(df, "_subvote_table"):
        spark.sql(f"DROP TABLE IF EXISTS {df._subvote_table}")
    delete(spark, df._subvote_path)


def delete(spark: SparkSession, name: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(name)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """Write a small file whole or not at all: under another name, then renamed."""
    fs_path = spark._jvm.org.apache.hadoop.fs.Path
    fs = fs_path(path).getFileSystem(spark._jsc.hadoopConfiguration())
    temporary = fs_path(f"{path}.{uuid.uuid4().hex}.tmp")
    out = fs.create(temporary)
    out.write(bytearray(text.encode()))
    out.close()
    if not fs.rename(temporary, fs_path(path)):
        raise OSError(f"{path} is there already")


def list_names(spark: SparkSession, folder: str) -> list[str]:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    return sorted(f.getPath().getName() for f in fs.listStatus(path)) if fs.exists(path) else []


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
