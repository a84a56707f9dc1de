"""Tables of a data folder with fixed schemas, and files of other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str, checked: bool = False) -> DataFrame:
    """Parquet scan of a table; with `checked` its column names must be the known ones.

    Types stay those of the files (integer widths and time zones differ between writers).
    """
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if checked:
        known = [c.split()[0] for c in SCHEMAS[name].split(", ")]
        if sorted(df.columns) != sorted(known):
            raise ValueError(f"{name} has columns {df.columns}, expected {known}")
    return df


def register(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """Temporary views of the tables for spark.sql."""
    for name in names or SCHEMAS:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options: str) -> DataFrame:
    """CSV, JSON, ORC or Parquet with an explicit schema where the format has none."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, path: str, fmt: str, mode: str = "overwrite", partition_by: list[str] | None = None, **options: str) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int, sort_by: str) -> None:
    """A bucketed table: joins and aggregations on `key` need no shuffle afterwards."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(sort_by).saveAsTable(table)
