"""Which of given pairs the method finds, without laying out its other pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import BlockingConfig
from ..plans.storage import release, settle
from . import rounds


class Asked:
    """The rounds of rib.run() over an index (rid, keys), counted exactly, for pairs that come from elsewhere. Two records are in
    a block that is compared if they share a key that is not over-size, so only over-size keys are kept: written are a record's
    other keys, hashed, and the numbers of those with which it goes on, and no block and no pair beside those asked for."""

    def __init__(self, index: DataFrame, cfg: BlockingConfig):
        self.cfg = cfg
        post = index.select("rid", F.explode("keys").alias("key"))
        self.over = self._numbered(rounds.key_stats(post).filter(F.col("size") > cfg.block_cap), ["key"])
        told = post.join(self._hint(self.over).select("key", "at", "going"), "key", "left")
        fit, k = F.when(F.col("at").isNull(), F.xxhash64("key")), F.when(F.col("going"), F.col("at"))
        held = told.groupBy("rid").agg(F.collect_list(fit).alias("fit"), F.array_sort(F.collect_list(k)).alias("k"))
        self.held = settle(held.select("rid", "fit", self._within("k")), "held")

    def _within(self, k: str):
        """Records of more than key_cap keys, or fewer than two, do not go on."""
        return F.when(F.size(k).between(2, self.cfg.key_cap), F.col(k)).alias("k")

    def _hint(self, over: DataFrame) -> DataFrame:
        return F.broadcast(over) if over.count() <= self.cfg.broadcast_keys else over

    def _numbered(self, stats: DataFrame, key: list[str]) -> DataFrame:
        """(key, at, size, going) of over-size keys: those go on that are smaller than their parents, and the first of those with
        the same records."""
        moves = rounds.shrinks(F.col("size"), F.col("psize"), self.cfg)
        made = settle(stats.withColumn("moves", moves).withColumn("at", F.monotonically_increasing_id()), "counted")
        first = made.filter("moves").groupBy("fp", "size").agg(F.min("at").alias("at")).select("at", F.lit(True).alias("first"))
        out = settle(made.join(first, "at", "left").select(*key, "at", "size", F.coalesce("first", F.lit(False)).alias("going")), "numbered")
        release(made)
        return out

    def records(self) -> DataFrame:
        """(rid) of records that can have a pair: those with a key that is not over-size, or with over-size keys to intersect."""
        return self.held.filter("size(fit) > 0 OR k IS NOT NULL").select("rid")

    def of(self, pairs: DataFrame) -> DataFrame:
        """Those of pairs (rid1, rid2) that share a block of fit size in any round."""
        side = lambda held, n, *more: held.select(F.col("rid").alias(f"rid{n}"), *[F.col(c).alias(f"{c}{n}") for c in more])
        asked = pairs.select("rid1", "rid2")
        tested = asked.join(side(self.held, 1, "fit", "k"), "rid1").join(side(self.held, 2, "fit", "k"), "rid2")
        found = F.arrays_overlap("fit1", "fit2")
        tested = settle(tested.select("rid1", "rid2", found.alias("found"), (F.col("k1").isNotNull() & F.col("k2").isNotNull()).alias("live")), "tested")
        held, over, out = self.held.filter("k IS NOT NULL").select("rid", "k"), self.over, [tested.filter("found").select("rid1", "rid2")]
        for _ in range(self.cfg.max_rounds):
            live = tested.filter("live AND NOT found").select("rid1", "rid2")
            if not live.limit(1).count():
                return self._together(out)
            over, after = self._next(held, over)
            both = held.join(after.withColumnRenamed("k", "next"), "rid", "left").withColumn("o", F.coalesce("o", F.array().cast("array<bigint>")))
            tested = live.join(side(both, 1, "k", "o", "next"), "rid1").join(side(both, 2, "k", "o", "next"), "rid2")
            m, over_size = F.size(F.array_intersect("k1", "k2")), F.size(F.array_intersect("o1", "o2"))
            tested = settle(tested.select("rid1", "rid2", (m * (m - 1) / 2 > over_size).alias("found"), (F.col("next1").isNotNull() & F.col("next2").isNotNull()).alias("live")), "tested")
            out.append(tested.filter("found").select("rid1", "rid2"))
            held = after.filter("k IS NOT NULL").select("rid", "k")
        raise RuntimeError(f"over-size blocks are left after {self.cfg.max_rounds} rounds")

    def _next(self, held: DataFrame, over: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Over-size intersections of every two keys that a record goes on with, and (rid, o, k): a record's numbers of them, and
        of those that it goes on with."""
        first = held.select("rid", "k", F.posexplode(F.slice("k", F.lit(1), F.size("k") - 1)).alias("nth", "a"))
        kids = first.select("rid", "a", F.explode(F.slice("k", F.col("nth") + 2, F.size("k"))).alias("b"))
        counted = kids.groupBy("a", "b").agg(F.count("*").alias("size"), F.bit_xor(F.xxhash64("rid")).alias("fp")).filter(F.col("size") > self.cfg.block_cap)
        size = lambda n: over.select(F.col("at").alias(n), F.col("size").alias(f"size_{n}"))
        sized = counted.join(size("a"), "a").join(size("b"), "b").withColumn("psize", F.least("size_a", "size_b"))
        made = self._numbered(sized.select("a", "b", "size", "fp", "psize"), ["a", "b"])
        told = kids.join(self._hint(made).select("a", "b", "at", "going"), ["a", "b"])
        after = told.groupBy("rid").agg(F.collect_list("at").alias("o"), F.array_sort(F.collect_list(F.when(F.col("going"), F.col("at")))).alias("k"))
        return made, settle(after.select("rid", "o", self._within("k")), "held")

    @staticmethod
    def _together(out: list[DataFrame]) -> DataFrame:
        every = out[0]
        for more in out[1:]:
            every = every.unionByName(more)
        return every
