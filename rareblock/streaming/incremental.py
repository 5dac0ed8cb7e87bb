"""Key statistics and postings kept up to date as records arrive.

The state is a table (key, size, fp) and a table (rid, key) per batch; sizes add and fingerprints XOR, so batches
merge in any order, and a key moves from fit to over-size, its postings of all batches with it, when its merged
size crosses the cap.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import keys as block_keys
from ..operators import rounds


class IncrementalKeys:
    """Use absorb as the function of foreachBatch. A batch that is handed over again replaces itself."""

    def __init__(self, path: str, rid: str, specs: list[block_keys.KeySpec]):
        self.path, self.rid, self.specs = path, rid, specs

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        postings = f"{self.path}/postings/batch={batch_id}"
        block_keys.postings(block_keys.build_index(batch, self.rid, self.specs)).write.mode("overwrite").parquet(postings)
        rounds.key_stats(batch.sparkSession.read.parquet(postings)).select("key", "size", "fp").write.mode("overwrite").parquet(f"{self.path}/stats/batch={batch_id}")

    def stats(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/stats").groupBy("key").agg(F.sum("size").alias("size"), F.bit_xor("fp").alias("fp"))

    def over(self, spark: SparkSession, cap: int) -> DataFrame:
        return self.stats(spark).filter(F.col("size") > cap)

    def split(self, spark: SparkSession, cap: int) -> tuple[DataFrame, DataFrame]:
        """(fit, over) postings (rid, key, batch) as of now."""
        over = self.over(spark, cap).select("key")
        every = spark.read.parquet(f"{self.path}/postings")
        return every.join(over, "key", "left_anti").select("rid", "key", "batch"), every.join(over, "key", "left_semi").select("rid", "key", "batch")

    def moved(self, spark: SparkSession, cap: int, batch_id: int) -> DataFrame:
        """(rid, key, batch): postings of earlier batches whose key was fit before the batch and is over-size with it:
        what a consumer that compared them as fit must take back into the intersection."""
        by = spark.read.parquet(f"{self.path}/stats").filter(F.col("batch") <= batch_id).groupBy("key")
        sizes = by.agg(F.sum("size").alias("now"), F.sum(F.when(F.col("batch") < batch_id, F.col("size")).otherwise(0)).alias("before"))
        crossed = sizes.filter((F.col("now") > cap) & F.col("before").between(1, cap)).select("key")
        return spark.read.parquet(f"{self.path}/postings").filter(F.col("batch") < batch_id).join(crossed, "key", "left_semi").select("rid", "key", "batch")
