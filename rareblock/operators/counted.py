"""Distinct pairs of blocks, counted by ranges of records: no pair is a row, and none is shuffled."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import settle
from . import rounds

#: Level of true pairs; blocks have the levels below.
TRUE = 15
#: Pairs, repeats counted, that a task is meant to hold, and that it sorts at a time.
HELD, SORTED = 16_000_000, 4_000_000


def by_level(blocks: DataFrame, truth: DataFrame) -> DataFrame:
    """(level, pairs, hits) of blocks (level from 0 to 14, rids): how many distinct pairs have their least level there, and how
    many of the true pairs (rid1, rid2) among them; level TRUE has the true pairs of no block. A pair counts
    in the part of its lesser record, so of a block each part gets the members from its own first one on: less than
    one id per pair, as often as the block has parts."""
    told = truth.select(F.lit(TRUE).alias("level"), F.array_sort(F.array("rid1", "rid2")).alias("rids"))
    every = settle(blocks.select(F.col("level").cast("int").alias("level"), F.array_sort("rids").alias("rids")).unionByName(told), "levelled")
    many = every.agg(F.coalesce(F.sum(F.expr("cast(size(rids) as bigint) * (size(rids) - 1) div 2")), F.lit(0))).first()[0]
    parts = max(12, -(-many // HELD))
    at = every.withColumn("at", F.transform("rids", lambda r: F.pmod(F.xxhash64(r), F.lit(parts)).cast("int")))
    each = at.select("level", "rids", "at", F.explode(F.array_distinct(F.slice("at", F.lit(1), F.greatest(F.size("at") - 1, F.lit(0))))).alias("part"))
    first = F.array_position("at", F.col("part")).cast("int")
    sent = each.select("part", "level", F.slice("rids", first, F.size("rids")).alias("rids"), F.transform(F.slice("at", first, F.size("at")), lambda a: a == F.col("part")).alias("own"))
    made = sent.repartitionById(parts, F.col("part")).select("level", "rids", "own").mapInArrow(_count, "level int, pairs bigint, hits bigint")
    return made.groupBy("level").agg(F.sum("pairs").alias("pairs"), F.sum("hits").alias("hits"))


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = []
    for b in batches:
        lists = b.column(1)
        n = np.diff(lists.offsets.to_numpy())
        held.append((b.column(0).to_numpy(), n, lists.flatten().to_numpy(), b.column(2).flatten().to_numpy(zero_copy_only=False)))
    if not held:
        return
    level, n, rid, own = (np.concatenate(x) for x in zip(*held, strict=True))
    del held
    ids, rid = np.unique(rid, return_inverse=True)
    after = np.repeat(np.cumsum(n), n) - np.arange(len(rid)) - 1  # members behind
    level = np.repeat(level.astype("i8"), n)
    low = np.flatnonzero(own & (after > 0))
    low = low[np.argsort(rid[low], kind="stable")]
    pairs, hits = np.zeros(TRUE + 1, "i8"), np.zeros(TRUE + 1, "i8")
    before = np.append(0, np.cumsum(after[low]))
    ends = np.append(np.flatnonzero(np.diff(rid[low])) + 1, len(low)) if len(low) else []  # a record's rows stay together
    begin = 0
    while begin < len(low):
        till = ends[min(np.searchsorted(before[ends], before[begin] + SORTED), len(ends) - 1)]
        a, many = low[begin:till], after[low[begin:till]]
        left = np.repeat(a, many)
        right = np.arange(len(left)) - np.repeat(np.cumsum(many) - many, many) + left + 1
        x, y = rid[left], rid[right]
        code = np.sort(((x * len(ids) + y) << 4 | level[left])[x != y])
        pair = code >> 4
        fresh = np.flatnonzero(np.append(True, pair[1:] != pair[:-1])) if len(code) else np.empty(0, "i8")
        least = code[fresh] & 15
        last = code[np.append(fresh[1:], len(code)) - 1] & 15 if len(code) else least
        pairs += np.bincount(least, minlength=TRUE + 1)
        hits += np.bincount(least[last == TRUE], minlength=TRUE + 1)
        begin = till
    pairs[TRUE] = 0
    yield pa.RecordBatch.from_arrays([pa.array(np.arange(TRUE + 1), pa.int32()), pa.array(pairs), pa.array(hits)], ["level", "pairs", "hits"])


def capped(index: DataFrame, caps: list[int]) -> DataFrame:
    """(level, rids) of top-level blocks (rid, keys) of two records up to the largest cap; the level is the place of the least cap
    that keeps the block, caps ascending. Blocks above are counted and never collected."""
    post = index.select("rid", F.explode("keys").alias("key"))
    sizes = rounds.key_stats(post).filter(F.col("size").between(2, caps[-1]))
    level = F.lit(len(caps) - 1)
    for i in range(len(caps) - 2, -1, -1):
        level = F.when(F.col("size") <= caps[i], i).otherwise(level)
    kept = settle(sizes.select("key", level.alias("level")), "fit")
    return post.join(kept, "key").groupBy("key", "level").agg(F.collect_list("rid").alias("rids")).select("level", "rids")
