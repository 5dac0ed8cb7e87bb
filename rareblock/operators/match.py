"""After blocking: score candidate pairs, cluster the matches, keep one record of each cluster."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cluster import components


def attach(pairs: DataFrame, records: DataFrame, rid: str, columns: dict[str, Column]) -> DataFrame:
    """pairs with the columns of either side, numbered 1 and 2."""
    side = lambda n: records.select(F.col(rid).cast("bigint").alias(f"rid{n}"), *[c.alias(f"{name}{n}") for name, c in columns.items()])
    return pairs.join(side(1), "rid1").join(side(2), "rid2")


def score(pairs: DataFrame, records: DataFrame, rid: str, columns: dict[str, Column], rule: Column, least: float) -> DataFrame:
    """(rid1, rid2, score) of pairs whose rule over the numbered columns reaches least."""
    return attach(pairs.select("rid1", "rid2"), records, rid, columns).select("rid1", "rid2", F.round(rule, 6).alias("score")).filter(F.col("score") >= least)


def rarity(values: DataFrame, column: str) -> DataFrame:
    """(value, weight): how much an agreement on a value tells, ln(rows / rows with it)."""
    n = values.agg(F.count("*").alias("n"))
    return values.groupBy(F.col(column).alias("value")).agg(F.count("*").alias("df")).crossJoin(F.broadcast(n)).select("value", F.log(F.col("n") / F.col("df")).alias("weight"))  # one row


def score_blocks(packed: DataFrame, records: DataFrame, rid: str, column: str, rule: Callable[[object, object], float], least: float) -> DataFrame:
    """(rid1, rid2, score) straight from packed blocks (key, n, rids, bitmap): a block's values are gathered once,
    at most block_cap of them, and its set bits scored in place."""
    values = packed.select("key", "n", "rids", "bitmap", F.explode("rids").alias("rid")).join(records.select(F.col(rid).cast("bigint").alias("rid"), F.col(column).alias("v")), "rid")
    held = values.groupBy("key").agg(F.first("n").alias("n"), F.first("bitmap").alias("bitmap"), F.array_sort(F.collect_list(F.struct("rid", "v"))).alias("m"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, s = [], [], []
            for row in batch.to_pylist():
                m, bit = row["m"], 0
                for i in range(len(m)):
                    for j in range(i + 1, len(m)):
                        if row["bitmap"] is None or row["bitmap"][bit >> 3] >> (bit & 7) & 1:
                            x = rule(m[i]["v"], m[j]["v"])
                            if x >= least:
                                a.append(m[i]["rid"]), b.append(m[j]["rid"]), s.append(x)
                        bit += 1
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(s, pa.float64())], ["rid1", "rid2", "score"])

    return held.mapInArrow(run, "rid1 bigint, rid2 bigint, score double")


def clusters(matches: DataFrame) -> DataFrame:
    """(rid, cluster): connected components of the matched pairs, named by their least id."""
    return components(matches, "rid1", "rid2").select(F.col("node").alias("rid"), F.col("component").alias("cluster"))


def survivors(records: DataFrame, rid: str, clustered: DataFrame) -> DataFrame:
    """Records that are in no cluster or have their cluster's least id."""
    gone = clustered.filter("rid <> cluster").select(F.col("rid").alias("_gone"))
    return records.join(gone, records[rid] == gone["_gone"], "left_anti")
