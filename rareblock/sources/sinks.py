"""Writing postings, blocks and pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write(df: DataFrame, path: str, by: str | None = None, fmt: str = "parquet", mode: str = "errorifexists", rows_per_file: int = 10_000_000) -> None:
    """Files of bounded rows. by 'key_prefix' lays rows out by the first byte of their key, so that a reader of a
    share of the keys prunes; any other name is a column to partition by."""
    writer = df
    if by == "key_prefix":
        writer = df.withColumn("key_prefix", F.substring(F.hex("key"), 1, 2)).repartition("key_prefix")
    out = writer.write.format(fmt).mode(mode).option("maxRecordsPerFile", rows_per_file)
    (out.partitionBy(by) if by else out).save(path)


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int) -> None:
    """A table bucketed and sorted by a column: joins on it need no shuffle later."""
    df.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").format("parquet").saveAsTable(table)
