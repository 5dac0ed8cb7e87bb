"""Joins that Spark has no operator for, as equi-joins on bins or as windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def band_join(df: DataFrame, rid: str, value: Column, within: float, same: list[str]) -> DataFrame:
    """(rid1, rid2) of rows equal on the columns ``same`` whose values differ by at most ``within``: a row meets
    its own bin and the next, so no pair is compared that is over two bins apart."""
    width = within if within > 0 else 1
    binned = df.select(F.col(rid).alias("r"), value.alias("v"), *same).withColumn("bin", F.floor(F.col("v") / width).cast("bigint"))
    left = binned.select(F.col("r").alias("rid1"), F.col("v").alias("v1"), *same, F.explode(F.array("bin", F.col("bin") + 1, F.col("bin") - 1)).alias("bin"))
    right = binned.select(F.col("r").alias("rid2"), F.col("v").alias("v2"), *same, "bin")
    return left.join(right, [*same, "bin"]).filter((F.col("rid1") < F.col("rid2")) & (F.abs(F.col("v1") - F.col("v2")) <= within)).select("rid1", "rid2")


def as_of(df: DataFrame, key: str, order: list[str], value: Column) -> Column:
    """The last non-null value among earlier rows of the key."""
    return F.last(value, ignorenulls=True).over(Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
