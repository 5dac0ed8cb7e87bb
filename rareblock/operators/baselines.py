"""Baselines: static keys, all pairs, size threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import BlockingConfig
from . import keys as block_keys
from . import rib, rounds


def static_pairs(df: DataFrame, rid: str, columns: list[str]) -> DataFrame:
    """All pairs equal on every one of the columns; nulls equal nothing."""
    side = lambda name: df.select(F.col(rid).cast("bigint").alias(name), *[F.col(c).alias(f"k{i}") for i, c in enumerate(columns)])
    return side("rid1").join(side("rid2"), [f"k{i}" for i in range(len(columns))]).filter("rid1 < rid2").select("rid1", "rid2")


def all_pairs(index: DataFrame) -> DataFrame:
    """Distinct pairs that share any key, whatever the block's size. Quadratic in the largest block: meant for
    small tables; all_pairs_cardinality() says what it would make."""
    post = block_keys.postings(index)
    both = post.select(F.col("rid").alias("rid1"), "key").join(post.select(F.col("rid").alias("rid2"), "key"), "key")
    return both.filter("rid1 < rid2").select("rid1", "rid2").distinct()


def all_pairs_cardinality(index: DataFrame) -> DataFrame:
    """keys (of two records at least) and comparisons, the sum of n * (n - 1) / 2, in decimals: the sum nears the
    range of a BIGINT on the largest tables."""
    sizes = block_keys.postings(index).groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    return sizes.agg(F.count("*").alias("keys"), F.coalesce(F.sum(F.expr("cast(n as decimal(38,0)) * (n - 1) / 2").cast("decimal(38,0)")), F.lit(0)).alias("comparisons"))


def fit_blocks(index: DataFrame, cap: int) -> DataFrame:
    """(key, size, rids) of top-level blocks of two to cap records. Sizes are counted with partial aggregates
    first, so the ids of over-size blocks are never collected."""
    post = block_keys.postings(index)
    sizes = rounds.key_stats(post).filter(F.col("size").between(2, cap)).select("key")
    held = post.join(sizes, "key", "left_semi").groupBy("key").agg(F.array_sort(F.collect_set("rid")).alias("rids"))
    return held.select("key", F.size("rids").cast("bigint").alias("size"), "rids").filter("size > 1")


def cap_drop(index: DataFrame, cap: int = 500) -> DataFrame:
    """Threshold blocking: distinct pairs of blocks up to cap records; larger blocks are discarded."""
    return rib.pairs_of(fit_blocks(index, cap), BlockingConfig()).select("rid1", "rid2")
