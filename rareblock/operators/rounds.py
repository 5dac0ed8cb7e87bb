"""The steps of one round: count keys, drop duplicates, tell fit from over-size, intersect locally."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import BlockingConfig
from ..functions.hashing import child_key


def weight(df: DataFrame) -> list[str]:
    """["n"] where a row stands for n records of equal keys, else nothing."""
    return ["n"] if "n" in df.columns else []


def seeded(index: DataFrame) -> DataFrame:
    """(rid, key, psize) of a top-level index, and n of one of classes; top-level keys have no parent. A record's entries stay together,
    in rows of one task, so their ids compress to almost nothing when written."""
    return index.select("rid", *weight(index), F.explode("keys").alias("key"), F.lit(None).cast("bigint").alias("psize"))


def key_stats(long_df: DataFrame, id_hash=None) -> DataFrame:
    """(key, size, fp, psize): exact size, and XOR of hashed ids, in one aggregate that is combined before the
    shuffle: a key sends one row per task, however large its block. Sizes are of records, fingerprints of rows."""
    h = id_hash or F.xxhash64
    psize = F.min("psize") if "psize" in long_df.columns else F.lit(None).cast("bigint")
    size, lone = (F.sum("n"), [(F.count("*") == 1).alias("lone")]) if weight(long_df) else (F.count("*"), [])
    return long_df.groupBy("key").agg(size.alias("size"), F.bit_xor(h(F.col("rid"))).alias("fp"), psize.alias("psize"), *lone)


def pivot_stats(long_df: DataFrame) -> DataFrame:
    """key_stats() the expensive way: the ids of every key are collected. Kept for comparison."""
    ids = long_df.groupBy("key").agg(F.array_sort(F.collect_list("rid")).alias("ids"), F.min("psize").alias("psize"))
    return ids.select("key", F.size("ids").cast("bigint").alias("size"), F.xxhash64("ids").alias("fp"), "psize")


def shrinks(size: Column, psize: Column, cfg: BlockingConfig) -> Column:
    """Whether a block is small enough beside its smaller parent, in integers; top-level blocks always are."""
    return psize.isNull() | (size * 1000 <= psize * cfg.shrink_thousandths)


def drop_twins(over: DataFrame) -> DataFrame:
    """Of over-size keys with the same records, the least key. Size goes into the group with the fingerprint, so
    that a chance XOR match of blocks of other sizes merges nothing."""
    return over.groupBy("fp", "size").agg(F.min("key").alias("key"), F.count("*").alias("copies"))


def classify(stats: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """(key, size, psize, kind) of over-size keys: 'over' goes on, 'twin' copies another, 'stalled' hardly
    shrank. Keys of fit size are not in it."""
    over = stats.filter(F.col("size") > cfg.block_cap).withColumn("moves", shrinks(F.col("size"), F.col("psize"), cfg))
    kept = drop_twins(over.filter("moves")).select("key", F.lit(True).alias("first"))
    kind = F.when(~F.col("moves"), "stalled").when(F.col("first"), "over").otherwise("twin")
    return over.join(kept, "key", "left").select("key", "size", "psize", kind.alias("kind"), *[c for c in ("lone",) if c in over.columns])


def intersect(over: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """(rid, key, psize) of the logical intersections of every two over-size keys a record has: no shuffle beyond
    that which gathers a record's over-size keys, (rid, key, size). Records with more than key_cap of them or
    fewer than two leave. Two explodes make the pairs, so that hashing them is compiled code. What intersects a block of one
    class has that class again; below a ratio of 1 the shrink test would stop it, over-size as it is, so it is not made."""
    n = weight(over)
    held = over.groupBy("rid", *n).agg(F.array_sort(F.collect_list(F.struct("key", "size", *(["lone"] if n else [])))).alias("k")).filter(F.size("k").between(2, cfg.key_cap))
    first = held.select("rid", *n, "k", F.posexplode(F.slice("k", F.lit(1), F.size("k") - 1)).alias("i", "a"))
    both = first.select("rid", *n, "a", F.explode(F.slice("k", F.col("i") + 2, F.size("k"))).alias("b"))
    if n and cfg.shrink_thousandths < 1000:
        both = both.filter("NOT a.lone AND NOT b.lone")
    return both.select("rid", *n, child_key(F.col("a.key"), F.col("b.key"), cfg.hash).alias("key"), F.least("a.size", "b.size").alias("psize"))


def windows(over: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """(rid, key) of blocks of block_cap records, cut in the order of ids from those members of an over-size block that
    have no other over-size key and so would never be compared. (rid, key, size) come in."""
    lone = over.groupBy("rid").agg(F.count("*").alias("n"), F.min("key").alias("key")).filter("n = 1")
    # A block may be any part of the table: ids are dealt into runs by a count per range of ids before they are numbered.
    spans = lone.withColumn("span", F.floor(F.col("rid") / (64 * cfg.block_cap)))
    before = Window.partitionBy("key").orderBy("span").rowsBetween(Window.unboundedPreceding, -1)
    starts = spans.groupBy("key", "span").agg(F.count("*").alias("n")).select("key", "span", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    nth = F.row_number().over(Window.partitionBy("key", "span").orderBy("rid")) - 1 + F.col("start")
    label = F.unhex(F.md5(F.concat(F.col("key"), F.floor(nth / cfg.block_cap).cast("string").cast("binary"))))
    return spans.join(starts, ["key", "span"]).select("rid", label.alias("key"))
