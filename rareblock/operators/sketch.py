"""Approximate counts and membership of keys: count-min sketch and Bloom filter.

Keys are folded to 64 bits; a collision of folds can only add to a count, so estimates stay one-sided.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(key: Column) -> Column:
    return F.xxhash64(key)


def shape(eps: float, confidence: float) -> tuple[int, int]:
    """(depth, width) of the sketch with these bounds."""
    return math.ceil(-math.log(1 - confidence) / math.log(2)), math.ceil(2 / eps)


def dense_bytes(eps: float, confidence: float) -> int:
    """Size of its table of 8-byte counters, which one task builds and every worker gets."""
    depth, width = shape(eps, confidence)
    return 8 * depth * width


def build(long_df: DataFrame, eps: float, confidence: float, seed: int = 42, key: str = "key") -> bytes:
    """One sketch per partition, merged; its size depends on eps and confidence alone."""
    return bytes(long_df.agg(F.count_min_sketch(fold(F.col(key)), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("s")).first()["s"])


class CountMin:
    """A sketch's binary form: version, total, depth, width, a multiplier per row, the table; big-endian."""

    def __init__(self, data: bytes):
        self.total = int.from_bytes(data[4:12], "big", signed=True)
        self.depth, self.width = (int.from_bytes(data[i : i + 4], "big") for i in (12, 16))
        self.multipliers = np.frombuffer(data, ">i8", self.depth, 20).astype("i8")
        self.table = np.frombuffer(data, ">i8", self.depth * self.width, 20 + 8 * self.depth).astype("i8").reshape(self.depth, self.width)

    def estimate(self, folded: np.ndarray) -> np.ndarray:
        least = np.full(len(folded), np.iinfo("i8").max)
        for row, a in zip(self.table, self.multipliers, strict=True):
            with np.errstate(over="ignore"):
                h = folded * a
                h = (h + (h >> 32)) & 0x7FFFFFFF
            least = np.minimum(least, row[h % self.width])
        return least


def estimator(spark, data: bytes):
    """A column function of folded keys, never below the true count. The sketch is broadcast once."""
    shipped = spark.sparkContext.broadcast(data)

    @F.pandas_udf("bigint")
    def estimate(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        sketch = CountMin(shipped.value)
        for folded in batches:
            yield pd.Series(sketch.estimate(folded.to_numpy("i8")))

    return lambda key: estimate(fold(key))


def bucket_table(long_df: DataFrame, depth: int, width: int, key: str = "key", bucket=None) -> DataFrame:
    """The sketch as a table (d, bucket, n): it merges in parallel and has no row for an empty bucket, which
    suits widths that no single task could hold. bucket(d, key) defaults to a seeded 64-bit hash."""
    at = bucket or (lambda d, k: F.pmod(F.xxhash64(d, k), F.lit(width)))
    rows = long_df.select(F.explode(F.sequence(F.lit(0), F.lit(depth - 1))).alias("d"), F.col(key).alias("k"))
    return rows.select("d", at(F.col("d"), F.col("k")).cast("bigint").alias("bucket")).groupBy("d", "bucket").agg(F.count("*").alias("n"))


def maybe_above(long_df: DataFrame, cap: int, eps: float, confidence: float, broadcast_rows: int, keep) -> DataFrame:
    """long_df with a column ``maybe``: whether all buckets of the row's key hold more than cap. Buckets are counted as a
    table, of any width; only those above cap are looked up, a join a row of the sketch, and broadcast while their
    counted number allows. As with the sketch, no key of more than cap rows is missed."""
    depth, width = shape(eps, confidence)
    at = lambda d: F.pmod(F.xxhash64(F.lit(d), F.col("key")), F.lit(width)).cast("bigint")
    full = keep(bucket_table(long_df, depth, width).filter(F.col("n") > cap).select("d", "bucket"), "full-buckets")
    hint = F.broadcast if full.count() <= broadcast_rows else (lambda df: df)
    out = long_df.withColumn("maybe", F.lit(True))
    for d in range(depth):
        mine = hint(full.filter(F.col("d") == d).select(F.col("bucket").alias("full")))
        out = out.withColumn("at", at(d)).join(mine, F.col("at") == F.col("full"), "left").withColumn("maybe", F.col("maybe") & F.col("full").isNotNull()).drop("at", "full")
    return out


class Bloom:
    """A bit set with two-hash probing; no false negatives."""

    def __init__(self, expected: int, fpp: float):
        self.bits = max(64, int(math.ceil(-max(1, expected) * math.log(fpp) / math.log(2) ** 2)))
        self.probes = max(1, round(self.bits / max(1, expected) * math.log(2)))
        self.words = np.zeros(-(-self.bits // 64), "u8")

    def _places(self, folded: np.ndarray) -> Iterator[np.ndarray]:
        h = folded.astype("u8")
        other = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD) | np.uint64(1)
        for i in range(self.probes):
            yield (h + np.uint64(i) * other) % np.uint64(self.bits)

    def add(self, folded: np.ndarray) -> None:
        for at in self._places(folded):
            np.bitwise_or.at(self.words, (at >> np.uint64(6)).astype("i8"), np.uint64(1) << (at & np.uint64(63)))

    def holds(self, folded: np.ndarray) -> np.ndarray:
        out = np.ones(len(folded), bool)
        for at in self._places(folded):
            out &= (self.words[(at >> np.uint64(6)).astype("i8")] >> (at & np.uint64(63)) & np.uint64(1)).astype(bool)
        return out


def bloom_of(keys: DataFrame, fpp: float, key: str = "key", most: int = 20_000_000) -> Bloom:
    """Filter over a table of keys whose count is checked: 20 million take 96 MB at 1e-8."""
    n = keys.count()
    if n > most:
        raise ValueError(f"{n} keys are too many for one Bloom filter; use membership='join'")
    out = Bloom(n, fpp)
    out.add(keys.select(fold(F.col(key)).alias("f")).toPandas()["f"].to_numpy("i8"))
    return out


def bloom_test(spark, bloom: Bloom):
    shipped = spark.sparkContext.broadcast(bloom)

    @F.pandas_udf("boolean")
    def holds(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for folded in batches:
            yield pd.Series(shipped.value.holds(folded.to_numpy("i8")))

    return lambda key: holds(fold(key))
