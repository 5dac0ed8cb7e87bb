"""From blocks to distinct pairs, and pairs packed by block."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def expand(blocks: DataFrame, cross=None) -> DataFrame:
    """(rid1, rid2, key, size), rid1 < rid2, of blocks (key, size, rids sorted). cross(a, b), if given, says which
    pairs count, as for two sources."""
    first = blocks.select("key", "size", "rids", F.posexplode(F.slice("rids", F.lit(1), F.col("size").cast("int") - 1)).alias("i", "rid1"))
    out = first.select("key", "size", "rid1", F.explode(F.slice("rids", F.col("i") + 2, F.col("size").cast("int"))).alias("rid2")).select("rid1", "rid2", "key", "size")
    return out if cross is None else out.filter(cross(F.col("rid1"), F.col("rid2")))


def dedupe(pairs: DataFrame) -> DataFrame:
    """Each pair once, with the largest block it is in; of equal ones, the least key. Shuffles all pairs."""
    best = pairs.groupBy("rid1", "rid2").agg(F.min(F.struct((-F.col("size")).alias("s"), F.col("key").alias("k"))).alias("b"))
    return best.select("rid1", "rid2", F.col("b.k").alias("key"), (-F.col("b.s")).alias("size"))


def propagate(blocks: DataFrame, cross=None) -> DataFrame:
    """dedupe(expand(blocks)) without a shuffle of pairs. Every record's blocks are ranked, largest first; each
    posting takes the ranks before it into its block, and a pair stays where its records share none of them.
    What is shuffled are postings: n rows of a block instead of n * (n - 1) / 2."""
    post = blocks.select("key", "size", F.explode("rids").alias("rid"))
    ranked = post.groupBy("rid").agg(F.array_sort(F.collect_list(F.struct((-F.col("size")).alias("s"), F.col("key").alias("k")))).alias("r"))
    tagged = ranked.select("rid", F.transform("r", lambda x: F.xxhash64(x["k"])).alias("h"), F.posexplode("r").alias("at", "x"))
    member = F.struct("rid", F.slice("h", F.lit(1), F.col("at")).alias("before"))
    back = tagged.groupBy(F.col("x.k").alias("key"), (-F.col("x.s")).alias("size")).agg(F.array_sort(F.collect_list(member)).alias("m"))
    first = back.select("key", "size", "m", F.posexplode(F.slice("m", F.lit(1), F.col("size").cast("int") - 1)).alias("i", "a"))
    both = first.select("key", "size", "a", F.explode(F.slice("m", F.col("i") + 2, F.col("size").cast("int"))).alias("b"))
    out = both.filter(~F.arrays_overlap("a.before", "b.before")).select(F.col("a.rid").alias("rid1"), F.col("b.rid").alias("rid2"), "key", "size")
    return out if cross is None else out.filter(cross(F.col("rid1"), F.col("rid2")))


def bit_index(i: Column, j: Column, n: Column) -> Column:
    """Place of (i, j), i < j < n, in the rows of the strict upper triangle laid end to end."""
    rows_above = i * n - F.shiftright(i * (i + 1), 1)
    return (rows_above + j - i - 1).cast("bigint")


def pack(pairs: DataFrame) -> DataFrame:
    """(key, n, rids, edges, is_full, bits array<bigint>): a block's surviving pairs. n and rids are of the
    records that still have a pair in this block; bits are sorted places, null where all pairs survive."""
    held = pairs.groupBy("key").agg(F.collect_list(F.struct("rid1", "rid2")).alias("e"))
    rids = F.array_sort(F.array_union(F.transform("e", lambda e: e["rid1"]), F.transform("e", lambda e: e["rid2"])))
    sized = held.select("key", "e", rids.alias("rids")).withColumn("n", F.size("rids").cast("bigint"))
    full = F.size("e") == F.expr("n * (n - 1) div 2")
    place = lambda r: F.array_position("rids", r) - 1
    bits = F.array_sort(F.transform("e", lambda e: bit_index(place(e["rid1"]), place(e["rid2"]), F.col("n"))))
    return sized.select("key", "n", "rids", F.size("e").cast("bigint").alias("edges"), full.alias("is_full"), F.when(~full, bits).alias("bits"))


@F.pandas_udf(T.BinaryType())
def encode(bits: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
    """Bitmap of n * (n - 1) / 2 bits from places and n; null where places are null."""
    for places, n in bits:
        out = []
        for p, k in zip(places, n, strict=True):
            if p is None:
                out.append(None)
                continue
            flags = np.zeros(int(k) * (int(k) - 1) // 2, bool)
            flags[np.asarray(p, "i8")] = True
            out.append(np.packbits(flags, bitorder="little").tobytes())
        yield pd.Series(out)


@F.pandas_udf(T.ArrayType(T.LongType()))
def decode(maps: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
    """Places of the set bits; all places where the bitmap is null."""
    for bitmaps, n in maps:
        out = []
        for b, k in zip(bitmaps, n, strict=True):
            total = int(k) * (int(k) - 1) // 2
            out.append(np.arange(total) if b is None else np.flatnonzero(np.unpackbits(np.frombuffer(b, "u1"), bitorder="little")[:total]))
        yield pd.Series(out)


def unpack(packed: DataFrame) -> DataFrame:
    """(rid1, rid2, key) of packed blocks (key, n, rids, bitmap)."""
    grid = F.expr("transform(sequence(1, size(rids) - 1), i -> transform(slice(rids, i + 1, size(rids)), r -> struct(rids[i - 1] as rid1, r as rid2)))")
    at = packed.select("key", "rids", decode("bitmap", "n").alias("places"))
    return at.select("key", F.flatten(grid).alias("all"), "places").select("key", F.explode("places").alias("p"), "all").select(F.expr("all[p].rid1").alias("rid1"), F.expr("all[p].rid2").alias("rid2"), "key")
