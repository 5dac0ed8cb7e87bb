"""Rare-intersection blocking: over-size blocks are intersected until they are small or stop shrinking."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import BlockingConfig
from ..plans.storage import claim, release, settle, settle_at
from . import keys as block_keys
from . import pairs as pair_ops
from . import rounds, sketch

_DIAGNOSTICS = "round int, counting string, twins bigint, stalled bigint, false_over bigint, sketch_bytes bigint, bloom_bytes bigint"
_REPORT = "round int, keys bigint, fit bigint, over bigint, pass_ratio bigint, survivors bigint, cut_records bigint, abandoned_over bigint"


@dataclass
class Run:
    """Fit postings (rid, key) of all rounds, and a row per round of a report and of diagnostics."""

    postings: DataFrame
    report: list[tuple] = field(default_factory=list)
    diagnostics: list[tuple] = field(default_factory=list)

    def blocks(self) -> DataFrame:
        """(key, size, rids): the inverted view, made once, without blocks of one record."""
        held = self.postings.groupBy("key").agg(F.array_sort(F.collect_set("rid")).alias("rids"))
        return held.select("key", F.size("rids").cast("bigint").alias("size"), "rids").filter("size > 1")

    def report_frame(self) -> DataFrame:
        return self.postings.sparkSession.createDataFrame(self.report, _REPORT)

    def diagnostics_frame(self) -> DataFrame:
        """Per round: how it counted, over-size keys that copy another or hardly shrank, keys that a sketch took for
        over-size and are not, and the bytes of sketch and Bloom filter; null where there was none."""
        return self.postings.sparkSession.createDataFrame(self.diagnostics, _DIAGNOSTICS)


def sketch_eps(cfg: BlockingConfig, n_postings: int) -> float:
    """The error, as a share of all postings, that keeps over-counts below a quarter of the cap."""
    return cfg.sketch_eps or cfg.block_cap / 4 / max(1, n_postings)


def counting_of(cfg: BlockingConfig, n_postings: int) -> str:
    """How a round counts. A sketch pays once most keys can be settled by it, and is of use only while its width keeps
    the error below the cap; that width grows with the postings, so beyond sketch_bytes 'auto' counts exactly,
    and 'sketch' takes the table of buckets, which no task holds whole."""
    fits = sketch.dense_bytes(sketch_eps(cfg, n_postings), cfg.sketch_confidence) <= cfg.sketch_bytes
    if cfg.counting == "auto":
        return "sketch" if n_postings > 50_000_000 and fits else "exact"
    return "buckets" if cfg.counting == "sketch" and not fits else cfg.counting


def _stamp(index: DataFrame, cfg: BlockingConfig) -> str:
    """Digest of settings, columns and rows of a run."""
    rows = index.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("rid", F.array_sort("keys")).cast("decimal(38,0)")), F.lit(0))).first()
    return hashlib.sha256(repr((cfg.but(checkpoint_dir=None), index.schema.json(), *map(str, rows))).encode()).hexdigest()


def run(index: DataFrame, cfg: BlockingConfig = BlockingConfig(), written: bool = False) -> Run:  # noqa: B008  frozen
    """All rounds over an index (rid, keys). Each round reads a written index, counts its keys with partial
    aggregates, joins the few over-size keys back, writes the fit postings and the next, smaller index; the round's
    other tables are then deleted. With a checkpoint_dir all stay, and finished steps of an earlier run of the same
    settings over the same index are read instead of made. written: the index is a written table, of which the first
    round needs no copy."""
    keep = (lambda df, name: settle_at(df, f"{cfg.checkpoint_dir}/{name}")) if cfg.checkpoint_dir else settle
    if cfg.checkpoint_dir:
        claim(index.sparkSession, cfg.checkpoint_dir, _stamp(index, cfg))
    current = rounds.seeded(index) if written else keep(rounds.seeded(index), "round-0")
    done = Run(None)
    for t in range(cfg.max_rounds):
        fit, over, row, used = _one_round(current, cfg, t, keep)
        if cfg.salvage == "windows":
            fit = fit.unionByName(keep(rounds.windows(over, cfg), f"salvage-{t}"))
        done.postings = fit if done.postings is None else done.postings.unionByName(fit)
        done.report.append(row[0])
        done.diagnostics.append(row[1])
        last = not row[0][5]
        before, current = current, None if last else keep(rounds.intersect(over, cfg), f"round-{t + 1}")
        for table in (before, *used):
            release(table)
        if last or not current.limit(1).count():
            return done
    raise RuntimeError(f"over-size blocks are left after {cfg.max_rounds} rounds")


def _one_round(current: DataFrame, cfg: BlockingConfig, t: int, keep) -> tuple[DataFrame, DataFrame, tuple, list[DataFrame]]:
    """Fit postings, postings that go on, the rows of report and diagnostics, and the tables that the next index makes
    needless."""
    long_df, settled, used = current, None, []
    total = long_df.count() if cfg.counting in ("auto", "sketch") else 0
    mode = counting_of(cfg, total)
    if mode in ("sketch", "buckets"):
        settled, long_df = rough_split(long_df, cfg.but(counting=mode), keep)
    stats = rounds.pivot_stats(long_df) if mode == "pivot" else rounds.key_stats(long_df)
    stats = keep(stats.filter("size > 1") if settled is None else stats, f"stats-{t}")
    over = keep(rounds.classify(stats, cfg), f"over-{t}")
    used += [stats, over]
    n_over, n_pass, n_kept = over.agg(F.count("*"), F.count_if(F.col("kind") != "stalled"), F.count_if(F.col("kind") == "over")).first()
    n_keys, n_fit = stats.agg(F.count("*"), F.count_if(F.col("size") <= cfg.block_cap)).first()
    rough = settled is not None
    bloom = sketch.Bloom(n_over, cfg.bloom_fpp).words.nbytes if cfg.membership == "bloom" else None
    told = (t, mode, n_pass - n_kept, n_over - n_pass, n_fit if rough else None, sketch.dense_bytes(sketch_eps(cfg, total), cfg.sketch_confidence) if mode == "sketch" else None, bloom)
    fit, going = split(long_df, over, cfg, n_over)
    if settled is not None:
        fit = fit.unionByName(settled)
    held = going.groupBy("rid").agg(F.count("*").alias("n"))
    cut, lone = held.agg(F.count_if(F.col("n") > cfg.key_cap), F.count_if(F.col("n") == 1)).first()
    counted = (t, None if rough else n_keys, None if rough else n_fit, n_over, n_pass, n_kept, cut, lone)
    return keep(fit, f"fit-{t}"), going, (counted, told), used


def rough_split(long_df: DataFrame, cfg: BlockingConfig, keep=settle) -> tuple[DataFrame, DataFrame]:
    """(fit postings, postings of maybe over-size keys) by a sketch, which never counts too few: what it calls
    fit is fit. Keys of estimate 1 are single and leave. With shrink_on 'estimate' keys that look too much like
    their parent leave here, among them some that the sketch merely over-counted. counting 'buckets' has no estimate,
    only whether it is above the cap, so single keys stay and the shrink test sees exact sizes."""
    eps = sketch_eps(cfg, long_df.count())
    if cfg.counting == "buckets":
        told = sketch.maybe_above(long_df, cfg.block_cap, eps, cfg.sketch_confidence, cfg.broadcast_keys, keep)
        return told.filter("NOT maybe").select("rid", "key"), told.filter("maybe").select("rid", "key", "psize")
    estimate = sketch.estimator(long_df.sparkSession, sketch.build(long_df, eps, cfg.sketch_confidence, cfg.sketch_seed))
    sized = long_df.withColumn("est", estimate(F.col("key")))
    fit = sized.filter((F.col("est") <= cfg.block_cap) & (F.col("est") > 1)).select("rid", "key")
    maybe = sized.filter(F.col("est") > cfg.block_cap)
    if cfg.shrink_on == "estimate":
        maybe = maybe.filter(rounds.shrinks(F.col("est"), F.col("psize"), cfg))
    return fit, maybe.select("rid", "key", "psize")


def split(long_df: DataFrame, over: DataFrame, cfg: BlockingConfig, n_over: int) -> tuple[DataFrame, DataFrame]:
    """(fit postings, postings of keys that go on with their size). Over-size keys are few and broadcast while
    their checked number allows; beyond that the join shuffles. membership 'bloom' asks a Bloom filter over
    all over-size keys first, as published; a false positive there loses a fit posting."""
    lone = [c for c in ("lone",) if c in over.columns]
    flags = over.select("key", F.col("size").alias("osize"), "kind", *lone)
    small = cfg.survivor_store == "broadcast" or cfg.survivor_store == "auto" and n_over <= cfg.broadcast_keys
    hint = F.broadcast if small else (lambda df: df)
    if cfg.membership == "bloom":
        inside = sketch.bloom_test(long_df.sparkSession, sketch.bloom_of(over, cfg.bloom_fpp))
        tested = long_df.withColumn("maybe", inside(F.col("key")))
        going = tested.filter("maybe").join(hint(flags.filter("kind = 'over'")), "key")
        return tested.filter("NOT maybe").select("rid", "key"), going.select("rid", "key", F.col("osize").alias("size"))
    n = rounds.weight(long_df)
    fit = long_df.join(hint(flags.select("key")), "key", "left_anti").select("rid", "key", *n)
    if cfg.survivor_store == "sketch":
        return fit, sketched_survivors(long_df, over, cfg)
    going = long_df.join(hint(flags.filter("kind = 'over'")), "key").select("rid", "key", *n, F.col("osize").alias("size"), *lone)
    return fit, going


def sketched_survivors(long_df: DataFrame, over: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """Postings of survivors by a count-min sketch of survivors alone, each added as often as its size: the sizes that go
    on are estimates, never too small, and some keys that are no survivors go on beside them. Their intersections are
    counted again in the next round, so they cost work and, through the shrink test, may let a child block pass
    that the exact size would stop; no survivor is lost. Its bytes do not depend on how many survive."""
    kept = over.filter("kind = 'over'").select("key", F.explode(F.sequence(F.lit(1), F.ceil(F.log2("size")).cast("int"))).alias("bit"))
    widest = cfg.sketch_bytes // (8 * sketch.shape(0.5, cfg.sketch_confidence)[0])
    eps = max(cfg.sketch_eps or 0, 2 / widest, 0.5 / max(1, kept.count()))
    estimate = sketch.estimator(long_df.sparkSession, sketch.build(kept, eps, cfg.sketch_confidence, cfg.sketch_seed))
    sized = long_df.select("rid", "key", estimate(F.col("key")).alias("bits")).filter("bits > 0")
    return sized.select("rid", "key", F.pow(F.lit(2), F.col("bits")).cast("bigint").alias("size"))


def candidate_pairs(df: DataFrame, rid, specs, cfg: BlockingConfig = BlockingConfig(), cross=None) -> DataFrame:  # noqa: B008
    """(rid1, rid2, key, size): distinct pairs of records that share a block of at most block_cap records after
    any number of intersections, each with its largest block."""
    return pairs_of(run(block_keys.build_index(df, rid, specs, cfg.hash, cfg.null_as_value), cfg).blocks(), cfg, cross)


def pairs_of(blocks: DataFrame, cfg: BlockingConfig, cross=None) -> DataFrame:
    """Distinct pairs of the blocks. 'auto' decides inside blocks while a record has few of them, since two
    records' lists are compared for every pair, and else shuffles pairs."""
    how = cfg.pair_dedup
    if how == "auto":
        entries, records = blocks.select("size", F.explode("rids").alias("rid")).agg(F.count("*"), F.approx_count_distinct("rid")).first()
        how = "propagate" if entries <= 32 * max(1, records) else "shuffle"
    return pair_ops.propagate(blocks, cross) if how == "propagate" else pair_ops.dedupe(pair_ops.expand(blocks, cross))


def class_edges(held: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """(rid1, rid2, n1, n2): the method's pairs as edges between classes (rid, keys, n) of records of equal keys, of a class
    with itself among them. Blocks are counted in records, so caps and ratios mean what they mean for records; what is
    written and shuffled grows with the classes."""
    if cfg.counting != "exact" or cfg.membership != "join" or cfg.survivor_store == "sketch" or cfg.salvage != "none":
        raise ValueError("classes are counted exactly, joined, and not salvaged")
    made = run(held.select("rid", "keys", "n"), cfg)
    between = pairs_of(made.blocks(), cfg).select("rid1", "rid2")
    side = lambda i: held.select(F.col("rid").alias(f"rid{i}"), F.col("n").alias(f"n{i}"))
    own = made.postings.filter("n > 1").select(F.col("rid").alias("rid1"), F.col("rid").alias("rid2"), F.col("n").alias("n1"), F.col("n").alias("n2")).distinct()
    return between.join(side(1), "rid1").join(side(2), "rid2").select("rid1", "rid2", "n1", "n2").unionByName(own)


def candidate_blocks(df: DataFrame, rid, specs, cfg: BlockingConfig = BlockingConfig()) -> DataFrame:  # noqa: B008
    """Packed blocks: key, n, rids, edges, is_full and bitmap (null where full)."""
    packed = pair_ops.pack(candidate_pairs(df, rid, specs, cfg))
    return packed.withColumn("bitmap", pair_ops.encode("bits", "n")).drop("bits")
