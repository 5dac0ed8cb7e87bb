"""Reading tables of records, and giving an id to those without one."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The given tables and their id columns.
IDS = {
    "region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey",
    "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id",
}
LINEITEM_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_shipdate")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Any format Spark reads; text-like formats need a schema, so that no file is read twice to guess one."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def hashed_rid(*columns: str) -> Column:
    """A 63-bit id from a row's own values: the same on every retry, without a shuffle."""
    return F.xxhash64(*[F.col(c) for c in columns]).bitwiseAND(F.lit(2**63 - 1))


def numbered_rid(df: DataFrame, *columns: str) -> DataFrame:
    """df with a dense rid in the order of the columns. One task numbers all rows: for tables of test size."""
    return df.withColumn("rid", F.row_number().over(Window.orderBy(*columns)).cast("bigint"))
