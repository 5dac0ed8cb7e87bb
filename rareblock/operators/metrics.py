"""Measures: pair completeness, pair quality, cardinality, cost and scaling."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .meta import PAIRS


def _share(hits: Column, total: Column) -> Column:
    return F.round(F.when(total > 0, hits / total).otherwise(0.0), 6)


def quality(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """pairs, hits, total (true pairs), pc and pq, six places. Both sides as distinct (rid1, rid2)."""
    p, t = pairs.select("rid1", "rid2").distinct(), truth.select("rid1", "rid2").distinct()
    marked = p.withColumn("p", F.lit(1)).join(t.withColumn("t", F.lit(1)), ["rid1", "rid2"], "full")
    sums = marked.agg(F.count("p").alias("pairs"), F.count_if(F.col("p").isNotNull() & F.col("t").isNotNull()).alias("hits"), F.count("t").alias("total"))
    return sums.select("pairs", "hits", "total", _share(F.col("hits"), F.col("total")).alias("pc"), _share(F.col("hits"), F.col("pairs")).alias("pq"))


def class_quality(edge: DataFrame, held: DataFrame, truth: DataFrame) -> DataFrame:
    """quality() of the pairs of records that edges (rid1, rid2, n1, n2) between the classes of meta.classes() stand for:
    true pairs are brought to their classes, and no pair is laid out."""
    of = lambda i: held.select(F.explode("members").alias(f"rid{i}"), F.col("rid").alias(f"class{i}"))
    t = truth.select("rid1", "rid2").distinct()
    at = t.join(of(1), "rid1").join(of(2), "rid2").groupBy(F.least("class1", "class2").alias("rid1"), F.greatest("class1", "class2").alias("rid2")).agg(F.count("*").alias("t"))
    sums = edge.join(at, ["rid1", "rid2"], "left").agg(F.coalesce(F.sum(F.expr(PAIRS)), F.lit(0)).alias("pairs"), F.coalesce(F.sum("t"), F.lit(0)).alias("hits"))
    both = sums.crossJoin(F.broadcast(t.agg(F.count("*").alias("total"))))  # one row
    return both.select("pairs", "hits", "total", _share(F.col("hits"), F.col("total")).alias("pc"), _share(F.col("hits"), F.col("pairs")).alias("pq"))


def group_quality(edge: DataFrame, held: DataFrame, groups: DataFrame) -> DataFrame:
    """quality() of the pairs of records that edges (rid1, rid2, n1, n2) between classes stand for, where the true pairs are
    those of records of one group: held (rid, n, g) has the group of each class, null where it has no true pair, and groups
    (n) how many records each has. Neither kind of pair is laid out."""
    of = lambda i: held.select(F.col("rid").alias(f"rid{i}"), F.col("g").alias(f"g{i}"))
    many = lambda c: F.coalesce(F.sum(c), F.lit(0))
    sums = edge.join(of(1), "rid1").join(of(2), "rid2").agg(many(F.expr(PAIRS)).alias("pairs"), many(F.when(F.col("g1") == F.col("g2"), F.expr(PAIRS))).alias("hits"))
    both = sums.crossJoin(F.broadcast(groups.agg(many(F.expr("n * (n - 1) div 2")).alias("total"))))  # one row
    return both.select("pairs", "hits", "total", _share(F.col("hits"), F.col("total")).alias("pc"), _share(F.col("hits"), F.col("pairs")).alias("pq"))


def level_quality(found: DataFrame, upto: int) -> DataFrame:
    """quality() of the pairs of levels up to ``upto`` of counted.by_level()."""
    inside = F.col("level") <= upto
    many = lambda c: F.coalesce(F.sum(c), F.lit(0))
    sums = found.agg(many(F.when(inside, F.col("pairs"))).alias("pairs"), many(F.when(inside, F.col("hits"))).alias("hits"), many("hits").alias("total"))
    return sums.select("pairs", "hits", "total", _share(F.col("hits"), F.col("total")).alias("pc"), _share(F.col("hits"), F.col("pairs")).alias("pq"))


def pc(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """hits, total, value: the share of true pairs that are among the pairs."""
    return quality(pairs, truth).select("hits", "total", F.col("pc").alias("value"))


def pq(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """hits, total, value: the share of pairs that are true."""
    return quality(pairs, truth).select("hits", F.col("pairs").alias("total"), F.col("pq").alias("value"))


def pq_oracle(pairs: DataFrame, accepted: Column) -> DataFrame:
    """hits, total, value: the share of pairs that a frozen rule accepts, where no complete truth is known."""
    sums = pairs.agg(F.count_if(accepted).alias("hits"), F.count("*").alias("total"))
    return sums.select("hits", "total", _share(F.col("hits"), F.col("total")).alias("value"))


def reduction(pairs: Column, records: Column) -> Column:
    """Share of all record pairs that need no comparison."""
    return F.round(1 - pairs / (records * (records - 1) / 2), 6)


def f1(p: float, r: float) -> float:
    return 0.0 if p + r == 0 else 2 * p * r / (p + r)


def timed(make: Callable[[], DataFrame]) -> tuple[int, float]:
    """Rows and minutes of an action that writes nothing."""
    began = time.monotonic()
    rows = make().count()
    return rows, (time.monotonic() - began) / 60


def cloud_cost(minutes: float, nodes: int, usd_per_hour: float) -> float:
    return minutes / 60 * nodes * usd_per_hour


def scoring_days(pairs: int, microseconds: float, workers: int = 1) -> float:
    return pairs * microseconds / 1e6 / 86400 / workers


def scaling(points: DataFrame) -> DataFrame:
    """slope, intercept, r2 of minutes over millions of records, and loglog, the power of the growth."""
    return points.agg(
        F.round(F.regr_slope("minutes", "millions"), 6).alias("slope"), F.round(F.regr_intercept("minutes", "millions"), 6).alias("intercept"),
        F.round(F.regr_r2("minutes", "millions"), 6).alias("r2"), F.round(F.regr_slope(F.log("minutes"), F.log("millions")), 6).alias("loglog"),
    )


def match_operating_point(make: Callable[[float], DataFrame], target: int, grid: list[float]) -> float:
    """The setting of the grid whose pair count is nearest to target on a logarithmic scale; the first on a tie."""
    return nearest({x: make(x).count() for x in grid}, target)


def nearest(counts: dict[float, int], target: int) -> float:
    """match_operating_point() of counts that are known, by setting."""
    import math

    return min(counts, key=lambda x: abs(math.log(max(1, counts[x]) / max(1, target))))


def cost_model(sizes: DataFrame, microseconds: float, nodes: int, usd_per_hour: float) -> DataFrame:
    """name, value: what comparing blocks (size) exhaustively costs, the largest alone, and all in dollars, in years of one
    worker and in days of all nodes."""
    many = F.expr("cast(size * (size - 1) div 2 as decimal(38,0))")
    sums = sizes.agg(F.max(many).cast("double").alias("most"), F.sum(many).cast("double").alias("every"))
    seconds = lambda c: F.col(c) * microseconds / 1e6
    values = {
        "heavy_value_days": seconds("most") / 86400, "naive_scoring_dollars": seconds("every") / 3600 * usd_per_hour,
        "naive_scoring_worker_years": seconds("every") / 86400 / 365.25, "naive_scoring_days": seconds("every") / 86400 / nodes,
    }
    rows = F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.round(v, 3).alias("value")) for n, v in values.items()])).alias("r")
    return sums.select(rows).select("r.name", "r.value")
