"""Contiguous shards of near-equal bytes, cut at equal targets of a global prefix sum. SQL functions only.

Rows are ordered by hash range, and in a range by text and then id, so copies of a text lie side by side. The
order is dealt into cells: a cell is the rows of a range, and a text that alone is much of the table has cells of
its own, by id hash. Totals per cell give every cell its global start; inside a cell a running sum gives each
row its own. No task holds more than a cell.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import settle


def shard_by_bytes(docs: DataFrame, n_shards: int = 8, id_col: str = "doc_id", text_col: str = "text", rows_per_cell: int = 200_000, ranges: int = 1024) -> DataFrame:
    """Every row once: doc_id, size (UTF-8 bytes of the text plus 1; a null text has none), text_crc32, law
    'bytes', shard, slot (from 0 without gaps), grown_shard (null for this law).

    Row i goes to the shard in whose share of the total bytes its middle byte falls, so a shard differs from
    its target by one row at most at either end, and at most n_shards - 1 texts have copies in two shards or more.
    Ties in id and text are broken by nothing that matters: such rows are equal. An empty table gives no rows.
    ``ranges`` is the least number of ranges; it grows with the rows so that one has about ``rows_per_cell``.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    # The texts are read once; what follows works on 28 bytes a row.
    rows = settle(docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("content")), "rows")
    total_rows = rows.count()
    ranges = max(ranges, total_rows // rows_per_cell)
    limit = max(64, 4 * total_rows // ranges)
    rows = rows.withColumn("range", F.pmod(F.col("content"), F.lit(ranges)).cast("int"))
    # A quarter of the ranges at most, and so of the texts, have more rows than limit.
    hot_ranges = rows.groupBy("range").count().filter(F.col("count") > limit).select("range")
    hot_texts = rows.join(F.broadcast(hot_ranges), "range").groupBy("content").count().filter(F.col("count") > limit)
    hot_texts = hot_texts.select("content", (F.floor(F.col("count") / limit) + 1).alias("parts"))
    part = F.coalesce(F.pmod(F.xxhash64(F.lit("part"), F.col("doc_id")), F.col("parts")), F.lit(0)).cast("int")
    dealt = rows.join(F.broadcast(hot_texts), "content", "left").withColumns({"own": F.when(F.col("parts").isNotNull(), F.col("content")).otherwise(F.lit(0)), "hot": F.col("parts").isNotNull(), "part": part}).drop("parts")

    cell = ["range", "hot", "own", "part"]
    totals = dealt.groupBy(*cell).agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))
    # One running sum over all cells: half as many again as there are ranges at most.
    before = Window.orderBy(*cell).rowsBetween(Window.unboundedPreceding, -1)
    starts = totals.select(*cell, F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("bytes_before"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("rows_before"))
    inside = Window.partitionBy(*cell).orderBy("content", "doc_id", "text_crc32", "size")
    upto = inside.rowsBetween(Window.unboundedPreceding, 0)
    total = totals.agg(F.coalesce(F.sum("bytes"), F.lit(0)).alias("total"))
    placed = (
        dealt.withColumns({"cum": F.sum("size").over(upto), "nth": F.row_number().over(inside) - 1})
        .join(starts, cell)
        .crossJoin(F.broadcast(total))  # one row
        .select(
            "doc_id", "size", "text_crc32",
            (F.col("rows_before") + F.col("nth")).alias("place"),
            F.least(F.lit(n_shards - 1), F.floor(F.lit(n_shards) * (F.col("bytes_before") + F.col("cum") - F.col("size") / 2) / F.col("total"))).cast("int").alias("shard"),
        )
    )
    placed = settle(placed, "shards")
    first = placed.groupBy("shard").agg(F.min("place").alias("first_place"))
    return placed.join(F.broadcast(first), "shard").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("place") - F.col("first_place")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )
