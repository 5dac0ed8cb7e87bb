"""What the operators share: table access and text folding."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import storage

__all__ = ["ascii_lower", "free_name", "held_out", "settle", "table"]

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()


_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Let Arrow batches of this session hold at most ``rows`` rows, for texts may be long: neither side of a
    Python worker then holds more than a few megabytes of them. A lower setting stays as it is."""
    now = int(spark.conf.get(_BATCH))
    if now <= 0 or now > rows:
        spark.conf.set(_BATCH, str(rows))


def settle(df: DataFrame, label: str = "step", batch_rows: int | None = None) -> DataFrame:
    """storage.settle() in small Arrow batches; batch_rows, for rows of megabytes, holds for this table alone."""
    conf = df.sparkSession.conf
    small_batches(df.sparkSession)
    before = conf.get(_BATCH)
    if batch_rows:
        conf.set(_BATCH, str(batch_rows))
    try:
        return storage.settle(df, label)
    finally:
        conf.set(_BATCH, before)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_name(df: DataFrame, name: str) -> str:
    """name, with underscores at its end until df has no column of that name in any case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def ascii_lower(text: Column) -> Column:
    """A-Z to a-z and nothing else, unlike lower(), which follows Unicode."""
    return F.translate(text, UPPER, LOWER)


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """Whether crc32 of the id as text leaves the remainder; a null id is hashed as the empty text."""
    return (F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % modulus) == remainder
