"""Connected components of a link table, by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import release, settle


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One star step over edges (a, b), a > b. Large: each node hangs its larger neighbours on its least
    neighbour; small: each node hangs its smaller neighbours, and itself, on the least of them."""
    ends = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    if large:
        ends = ends.unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    least = ends.groupBy("u").agg(F.min("v").alias("m"))
    if large:
        least = least.withColumn("m", F.least("m", "u"))
        moved = ends.filter("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        hung = ends.join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))
        moved = hung.unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return moved.filter("a <> b").distinct()


def components(links: DataFrame, left: str = "rid1", right: str = "rid2", max_steps: int = 60) -> DataFrame:
    """(node, component) for every node of a link, component being the least node reachable. Null ends,
    loops and repeated links change nothing. Each step is a written table; hubs are aggregated before any
    shuffle, and nothing but two sums comes to the driver."""
    a, b = F.col(left), F.col(right)
    edges = settle(links.filter(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct(), "links")
    mark = None
    for _ in range(max_steps):
        before, edges = edges, settle(_star(_star(edges, large=True), large=False), "stars")
        release(before)
        now = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components did not settle in {max_steps} steps")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component"))).distinct()
