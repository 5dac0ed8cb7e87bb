"""Exact Jaccard self-join, the ground truth of the text workloads."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import jaccard
from ..plans.storage import release, settle

#: Most tokens whose counts are sent to the tasks; it bounds a broadcast, not the join.
HOT = 500_000
#: Places of a record's parities, and of one with LARGE tokens or more: multiples of 64, the second of the first.
BITS, WIDE, LARGE = 384, 1536, 700


def frequent(hashed: DataFrame, most: int = HOT) -> tuple[np.ndarray, np.ndarray]:
    """(hashes ascending, counts) of the tokens that most records have, ``most`` at most, of (rid, h array<bigint>)."""
    counts = hashed.select(F.explode("h").alias("h")).groupBy("h").agg(F.count("*").alias("n")).filter("n > 1")
    found = counts.orderBy(F.desc("n"), "h").limit(most).toArrow()
    h, n = (found.column(c).to_numpy() for c in ("h", "n"))
    order = np.argsort(h)
    return h[order].astype("i8"), n[order].astype("i8")


def prefixes(hashed: DataFrame, least: float, most: int = HOT) -> DataFrame:
    """(token, rid, n, bits) of each record's first 1 + floor((1 - least) * n) tokens, in one order that all records share:
    two records at least ``least`` alike share one of them, whatever the order. Here it is by count, tokens outside
    the ``most`` frequent first, so that blocks are small. bits: the parity of the record's tokens in each of BITS or WIDE
    places."""
    hot = hashed.sparkSession.sparkContext.broadcast(frequent(hashed, most))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, counts = hot.value
        for batch in batches:
            lists = batch.column(1)
            flat, n = lists.flatten().to_numpy(zero_copy_only=False), np.diff(lists.offsets.to_numpy())
            row = np.repeat(np.arange(len(n)), n)
            at = np.minimum(np.searchsorted(known, flat), max(0, len(known) - 1))
            often = np.where(known[at] == flat, counts[at], 0) if len(known) else np.zeros(len(flat), "i8")
            order = np.lexsort((flat, often, row))
            nth = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)
            first = order[nth < np.repeat(_kept(n, least), n)]
            odd = np.bincount(row * WIDE + (flat.view("u8") >> np.uint64(40)).astype("i8") % WIDE, minlength=len(n) * WIDE) & 1
            wide = np.packbits(odd.astype(bool).reshape(-1, WIDE), axis=1)
            bits = pa.array([w.tobytes() if k >= LARGE else f.tobytes() for k, w, f in zip(n, wide, _folded(wide), strict=True)], pa.binary())
            at = pa.array(row[first])
            yield pa.RecordBatch.from_arrays([pa.array(flat[first]), batch.column(0).take(at), pa.array(n[row[first]].astype("i4")), bits.take(at)], ["token", "rid", "n", "bits"])

    return hashed.mapInArrow(run, "token bigint, rid bigint, n int, bits binary")


def _kept(n: np.ndarray, least: float) -> np.ndarray:
    return 1 + np.floor(n * (1 - least) + 1e-9).astype("i8")


def _folded(wide: np.ndarray) -> np.ndarray:
    """Parities in fewer places, each that of the places equal to it modulo their number."""
    return np.bitwise_xor.reduce(wide.reshape(len(wide), WIDE // BITS, wide.shape[1] * BITS // WIDE), axis=1)


def _met(few: DataFrame, least: float) -> DataFrame:
    """(rid1, n1, rid2, n2) of every two rows of a token, rid1 < rid2, whose sizes and parities allow the likeness: places
    of unlike parity are never more than the tokens that only one side has. Rows come sorted, a token's together."""

    def pairs(token, rid, n, sent) -> Iterator[pa.RecordBatch]:
        large = n >= LARGE
        wide = np.frombuffer(b"".join(sent[large]), "u8").reshape(-1, WIDE // 64)
        nth = np.where(large, np.cumsum(large) - 1, -1)  # a row's place in wide
        bits = np.empty((len(n), BITS // 64), "u8")
        bits[~large], bits[large] = np.frombuffer(b"".join(sent[~large]), "u8").reshape(-1, BITS // 64), _folded(wide)
        ends = np.flatnonzero(np.r_[token[1:] != token[:-1], True])
        after = np.repeat(ends, np.diff(np.r_[-1, ends])) - np.arange(len(token))  # rows of the same token behind
        live, far = np.arange(len(token)), 0
        while True:
            far += 1
            live = live[after[live] >= far]
            if not len(live):
                return
            for a in np.split(live, range(1_000_000, len(live), 1_000_000)):
                b = a + far
                most = (n[a] + n[b]) * (1 - least) / (1 + least) + 1e-9
                ok = (rid[a] != rid[b]) & (np.abs(n[a] - n[b]) <= most)
                a, b, most = a[ok], b[ok], most[ok]
                ok = np.bitwise_count(bits[a] ^ bits[b]).sum(1, dtype="i8") <= most
                a, b, most = a[ok], b[ok], most[ok]
                ok = (nth[a] < 0) | (nth[b] < 0)
                ok[~ok] = np.bitwise_count(wide[nth[a[~ok]]] ^ wide[nth[b[~ok]]]).sum(1, dtype="i8") <= most[~ok]
                a, b = a[ok], b[ok]
                if len(a):
                    flip = rid[a] > rid[b]
                    a, b = np.where(flip, b, a), np.where(flip, a, b)
                    yield pa.RecordBatch.from_arrays([pa.array(rid[a]), pa.array(n[a]), pa.array(rid[b]), pa.array(n[b])], ["rid1", "n1", "rid2", "n2"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []  # rows of tokens that may go on in the next batch
        for batch in batches:
            if not batch.num_rows:
                continue
            token, rid, n = (batch.column(i).to_numpy() for i in range(3))
            bits = batch.column(3).to_numpy(zero_copy_only=False)
            if token[-1] == token[0] and (not held or held[-1][0][0] == token[0]):
                held.append((token, rid, n, bits))  # one token from end to end
                continue
            last = int(np.flatnonzero(token != token[-1])[-1]) + 1 if token[0] != token[-1] else 0
            done = [*held, tuple(x[:last] for x in (token, rid, n, bits))]
            yield from pairs(*(np.concatenate(x) for x in zip(*done, strict=True)))
            held = [tuple(x[last:] for x in (token, rid, n, bits))]
        if held:
            yield from pairs(*(np.concatenate(x) for x in zip(*held, strict=True)))

    return few.repartition("token").sortWithinPartitions("token").mapInArrow(run, "rid1 bigint, n1 int, rid2 bigint, n2 int")


def hashes(df: DataFrame, rid: str, tokens: Column) -> DataFrame:
    """(rid, h): a record's tokens as 64-bit hashes, a written table."""
    return settle(df.select(F.col(rid).cast("bigint").alias("rid"), F.transform(tokens, lambda t: F.xxhash64(t)).alias("h")), "hashes")


def jaccard_join(df: DataFrame, rid: str, tokens: Column, least: float, hashed: DataFrame | None = None) -> DataFrame:
    """(rid1, rid2, jaccard), rid1 < rid2, of records at least ``least`` alike (above 0). Only a record's prefix of
    tokens is indexed, as 64-bit hashes, and shuffled once. Of two prefixes the one that ends first in the common order has
    met all its tokens that the other record holds, so two records have at most the tokens met and one side's rest in
    common. Candidates are confirmed on the tokens themselves, once for records of the same tokens, and only records that
    have a candidate send theirs. hashed: the records' hashes(), where the caller has them."""
    own = hashes(df, rid, tokens) if hashed is None else None
    hashed = own if hashed is None else hashed
    few = prefixes(hashed.filter("size(h) > 0 AND rid IS NOT NULL"), least)
    rest = lambda n: F.col(n) - 1 - F.floor(F.col(n) * (1 - least) + 1e-9)
    counted = _met(few, least).groupBy("rid1", "n1", "rid2", "n2").agg(F.count("*").alias("met"))
    likely = counted.filter(F.col("met") + F.greatest(rest("n1"), rest("n2")) >= (F.col("n1") + F.col("n2")) * (least / (1 + least)) - 1e-6)
    pairs = settle(likely.select("rid1", "rid2"), "candidates")
    release(own)
    asked = pairs.select(F.explode(F.array("rid1", "rid2")).alias("rid")).distinct()
    held = df.withColumn("_rid", F.col(rid).cast("bigint")).join(asked.withColumnRenamed("rid", "_rid"), "_rid", "left_semi").select(F.col("_rid").alias("rid"), tokens.alias("t"))
    some = settle(held.withColumn("kind", F.md5(F.to_json(F.array_sort("t")).cast("binary"))), "sets")
    named = lambda n: some.select(F.col("rid").alias(f"rid{n}"), F.col("kind").alias(f"kind{n}"))
    kinds = settle(pairs.join(named(1), "rid1").join(named(2), "rid2"), "kinds")
    unlike = kinds.filter("kind1 <> kind2").select(F.least("kind1", "kind2").alias("low"), F.greatest("kind1", "kind2").alias("high")).distinct()
    sent = some.groupBy("kind").agg(F.min("rid").alias("rid")).join(some.select("rid", "t"), "rid")
    full = lambda name, t: sent.select(F.col("kind").alias(name), F.col("t").alias(t))
    alike = unlike.join(full("low", "t1"), "low").join(full("high", "t2"), "high").select("low", "high", jaccard(F.col("t1"), F.col("t2")).alias("jaccard")).filter(F.col("jaccard") >= least - 1e-12)
    joined = kinds.filter("kind1 <> kind2").withColumns({"low": F.least("kind1", "kind2"), "high": F.greatest("kind1", "kind2")}).join(alike, ["low", "high"])
    return kinds.filter("kind1 = kind2").select("rid1", "rid2", F.lit(1.0).alias("jaccard")).unionByName(joined.select("rid1", "rid2", "jaccard"))
