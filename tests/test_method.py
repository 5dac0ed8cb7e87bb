"""Hand-checkable indexes, and properties of the method on random ones."""

import itertools
import random

import numpy as np
import pytest
from conftest import SMALL
from pyspark.sql import functions as F

from rareblock.config import AS_PUBLISHED, BlockingConfig
from rareblock.operators import baselines, keys, meta, rib, rounds, sketch
from rareblock.operators import pairs as pair_ops
from rareblock.operators.asked import Asked
from rareblock.operators.cluster import components
from rareblock.workloads import comparing

A, B, C, D = {1, 2, 3, 4}, {1, 2, 5, 6}, {1, 3, 4, 5, 6}, {5, 6}


def index(spark, blocks):
    rows = [(r, name) for name, members in blocks.items() for r in members]
    return keys.from_long(spark.createDataFrame(rows, "rid bigint, key string"), "rid", "key")


def pairs(spark, blocks, **settings):
    cfg = BlockingConfig(counting="exact").but(**settings)
    return {(r.rid1, r.rid2): r.size for r in rib.pairs_of(rib.run(index(spark, blocks), cfg).blocks(), cfg).collect()}


def test_two_generations(spark):
    x1 = {"A": A, "Z": A, "B": B, "C": C, "D": D}
    assert set(pairs(spark, x1, block_cap=2)) == {(1, 2), (5, 6)}
    assert pairs(spark, x1, block_cap=3) == {(1, 2): 2, (1, 3): 3, (1, 4): 3, (3, 4): 3, (1, 5): 3, (1, 6): 3, (5, 6): 3}
    assert baselines.all_pairs(index(spark, x1)).count() == 15
    assert {tuple(r) for r in baselines.cap_drop(index(spark, x1), 2).collect()} == {(5, 6)}


def test_stalled_block_gives_nothing(spark):
    assert pairs(spark, {"E": set(range(1, 21)), "F": {*range(1, 20), 21}}, block_cap=5) == {}


def test_ratio_is_met_by_equality(spark):
    x4 = {"E": set(range(1, 11)), "F": {*range(1, 10), 11}, "G": {1, 2, 12, 13, 14, 15}}
    assert set(pairs(spark, x4, block_cap=5)) == {(1, 2)}


def test_lower_key_cap_can_add_pairs(spark):
    assert set(pairs(spark, {"A": A, "B": B, "C": C}, block_cap=2, key_cap=2)) == {(3, 4), (5, 6)}


def test_equality_with_the_cap_is_fit(spark):
    assert set(pairs(spark, {"A": {1, 2, 3}, "B": {1, 2, 3, 4}}, block_cap=3)) == {(1, 2), (1, 3), (2, 3)}


def test_empty_index(spark):
    assert pairs(spark, {}, block_cap=3) == {}


@pytest.fixture(scope="module")
def random_blocks():
    rng = random.Random(7)
    return {f"k{i}": {rng.randrange(60) for _ in range(rng.choice([2, 3, 6, 15, 25]))} for i in range(40)}


def test_variants_agree(spark, random_blocks):
    exact = pairs(spark, random_blocks, block_cap=6)
    for change in ({"counting": "pivot"}, {"pair_dedup": "propagate"}, {"counting": "sketch"}, {"counting": "sketch", "sketch_eps": 0.05}, {"pair_dedup": "shuffle"}, {"survivor_store": "join"}, {"counting": "sketch", "membership": "bloom"}):
        assert pairs(spark, random_blocks, block_cap=6, **change) == exact, change
    assert set(pairs(spark, random_blocks, block_cap=6, hash="xx128")) == set(exact)


def test_nesting_of_methods(spark, random_blocks):
    i = index(spark, random_blocks)
    every = {tuple(r) for r in baselines.all_pairs(i).collect()}
    got, capped = set(pairs(spark, random_blocks, block_cap=6)), {tuple(r) for r in baselines.cap_drop(i, 6).collect()}
    assert capped <= got <= every
    assert {tuple(r) for r in meta.meta_blocking(i).collect()} <= every
    assert all(s <= 6 for s in pairs(spark, random_blocks, block_cap=6).values())


def test_published_settings_run(spark, random_blocks):
    cfg = AS_PUBLISHED.but(block_cap=6)
    assert rib.pairs_of(rib.run(index(spark, random_blocks), cfg).blocks(), cfg).count() > 0


def test_resume(spark, random_blocks, tmp_path):
    cfg = BlockingConfig(block_cap=6, counting="exact", checkpoint_dir=str(tmp_path / "run"))
    first = rib.run(index(spark, random_blocks), cfg).blocks().count()
    import shutil

    shutil.rmtree(tmp_path / "run" / "fit-1")
    assert rib.run(index(spark, random_blocks), cfg).blocks().count() == first


def test_bitmaps(spark, random_blocks):
    cfg = BlockingConfig(block_cap=6, counting="exact")
    got = rib.pairs_of(rib.run(index(spark, random_blocks), cfg).blocks(), cfg)
    packed = pair_ops.pack(got).withColumn("bitmap", pair_ops.encode("bits", "n")).drop("bits")
    assert {(r.rid1, r.rid2) for r in pair_ops.unpack(packed).collect()} == {(r.rid1, r.rid2) for r in got.collect()}
    assert packed.filter("is_full AND bitmap IS NOT NULL").count() == 0
    for n in (2, 5, 60):
        grid = spark.createDataFrame([(i, j, n) for i, j in itertools.combinations(range(n), 2)], "i bigint, j bigint, n bigint")
        assert [r[0] for r in grid.orderBy("i", "j").select(pair_ops.bit_index(F.col("i"), F.col("j"), F.col("n"))).collect()] == list(range(n * (n - 1) // 2))


def test_sketch_and_bloom(spark, random_blocks):
    long_df = rounds.seeded(index(spark, random_blocks))
    stats = rounds.key_stats(long_df)
    estimate = sketch.estimator(spark, sketch.build(long_df, 0.01, 0.99))
    assert stats.filter(estimate(F.col("key")) < F.col("size")).count() == 0
    bloom = sketch.Bloom(1000, 1e-4)
    bloom.add(np.arange(1000, dtype="i8"))
    assert bloom.holds(np.arange(1000, dtype="i8")).all()
    assert bloom.holds(np.arange(10_000, 60_000, dtype="i8")).mean() < 0.01


def test_keys(spark):
    df = spark.createDataFrame([(1, "foo", "foo"), (2, None, " "), (3, "Foo ", "bar"), (None, "x", "y")], "rid bigint, a string, b string")
    identity = keys.postings(keys.build_index(df, "rid", [keys.identity("a"), keys.identity("b")])).collect()
    assert len([r for r in identity if r.rid == 1]) == 2 and not [r for r in identity if r.rid == 2]
    by = {}
    for r in identity:
        by.setdefault(bytes(r.key), set()).add(r.rid)
    assert {1, 3} in by.values()
    token = keys.postings(keys.build_index(df, "rid", [keys.token(["a", "b"])])).collect()
    assert len([r for r in token if r.rid == 1]) == 1
    assert keys.build_index(df, "rid", [keys.identity("b")], null_as_value=True).filter("rid = 2").count() == 1
    with pytest.raises(ValueError):
        BlockingConfig(block_cap=1)


def test_components(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)] + [(900, 900), (None, 3)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "rid1 bigint, rid2 bigint")).collect()}
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    assert got == {x: find(x) for x in parent}
    assert components(spark.createDataFrame([], "rid1 bigint, rid2 bigint")).count() == 0


def test_sketch_stays_within_its_bytes():
    """By arithmetic: at the published sizes no mode asks for a sketch above its budget."""
    cfg = BlockingConfig()
    for n in (1_000, 60_000_000, 1_000_000_000, 30_000_000_000, 1_000_000_000_000):
        for asked in ("auto", "sketch", "exact", "pivot", "buckets"):
            mode = rib.counting_of(cfg.but(counting=asked), n)
            if mode == "sketch":
                assert sketch.dense_bytes(rib.sketch_eps(cfg, n), cfg.sketch_confidence) <= cfg.sketch_bytes == 256 * 2**20
            assert mode != "auto" and (asked in ("auto", "sketch") or mode == asked)
    at = lambda n, asked="auto": rib.counting_of(cfg.but(counting=asked), n)
    assert [at(1_000), at(60_000_000), at(1_000_000_000), at(30_000_000_000)] == ["exact", "sketch", "exact", "exact"]
    assert [at(n, "sketch") for n in (60_000_000, 1_000_000_000, 1_000_000_000_000)] == ["sketch", "buckets", "buckets"]
    assert sketch.shape(0.001, 0.999) == (10, 2000) and sketch.dense_bytes(0.001, 0.999) == 160_000


def test_buckets_survivor_sketch_and_salvage(spark, random_blocks):
    exact = pairs(spark, random_blocks, block_cap=6)
    assert pairs(spark, random_blocks, block_cap=6, counting="sketch", sketch_bytes=1) == exact
    assert pairs(spark, random_blocks, block_cap=6, counting="buckets", sketch_eps=0.05, broadcast_keys=0) == exact
    every = {tuple(r) for r in baselines.all_pairs(index(spark, random_blocks)).collect()}
    for change in ({}, {"sketch_eps": 0.2, "sketch_confidence": 0.5}):
        sketched = set(pairs(spark, random_blocks, block_cap=6, survivor_store="sketch", **change))
        assert set(exact) <= sketched <= every
    salvaged = set(pairs(spark, random_blocks, block_cap=6, salvage="windows"))
    assert set(exact) <= salvaged <= every
    lone = {"a": set(range(10)), "b": {20, 21}}
    assert pairs(spark, lone, block_cap=4) == pairs(spark, {"b": {20, 21}}, block_cap=4)
    assert set(pairs(spark, lone, block_cap=4, salvage="windows")) == {(20, 21)} | {(i, j) for i in range(10) for j in range(i + 1, 10) if i // 4 == j // 4}


def test_first_edges_by_narrowing(spark):
    rng = random.Random(3)
    edge = spark.createDataFrame([(i, j, round(rng.choice([0.25, 0.5, rng.random()]), 9)) for i in range(30) for j in range(i + 1, 30)], "rid1 bigint, rid2 bigint, w double")
    order = sorted(edge.collect(), key=lambda r: (-r["w"], r["rid1"], r["rid2"]))
    for k in (0, 1, 7, 100, 217, 434, 435, 9999):
        assert {tuple(r) for r in meta._first_rows(edge, k).collect()} == {tuple(r) for r in order[:k]}, k


def test_broadcast_meta_blocking(spark, random_blocks):
    i = index(spark, random_blocks)
    want = meta.edges(meta.block_postings(i, purge=None))
    got = meta.broadcast_edges(i, purge=None)
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    with pytest.raises(MemoryError):
        meta.broadcast_edges(i, most_bytes=100)


def test_resuming_another_run_is_refused(spark, random_blocks, tmp_path):
    i = index(spark, random_blocks)
    cfg = BlockingConfig(block_cap=6, counting="exact", checkpoint_dir=str(tmp_path))
    first = sorted(map(tuple, rib.run(i, cfg).postings.collect()))
    assert sorted(map(tuple, rib.run(i, cfg).postings.collect())) == first
    with pytest.raises(ValueError):
        rib.run(i, cfg.but(block_cap=7))
    with pytest.raises(ValueError):
        rib.run(i.filter("rid > 3"), cfg)


def test_finished_steps_are_deleted(spark, random_blocks):
    import glob

    from rareblock.plans import storage

    at = storage.shared_dir(spark).removeprefix("file://").removeprefix("file:")
    before = set(glob.glob(f"{at}/*-*"))
    rib.run(index(spark, random_blocks), BlockingConfig(block_cap=6, counting="exact"))
    made = {p.rsplit("/", 1)[1].split("-")[0] for p in set(glob.glob(f"{at}/*-*")) - before}
    assert made <= {"fit", "round"}  # of the rounds, the last index alone, which is empty


def test_copies_of_records_are_weighed_once(spark, tmp_path):
    """Edges between classes do not grow with the copies, and what they stand for equals the SQL over all records."""
    from conftest import SMALL
    from oracle import connect, same
    from rareblock.workloads import comparing
    from rareblock.workloads import fixtures as fx

    part, edges = spark.read.parquet(f"{SMALL}/part.parquet"), []
    for copies in (2, 4):
        d = str(tmp_path / str(copies))
        copied = part.crossJoin(spark.range(copies)).withColumn("p_partkey", (F.col("p_partkey") + F.col("id") * 1000).cast(part.schema["p_partkey"].dataType)).drop("id")
        copied.coalesce(1).write.parquet(f"{d}/part.parquet")
        edges.append(meta.edges(meta.block_postings(meta.classes(fx.part_index(spark, d)), purge=None)).count())
    assert edges[0] == edges[1]
    con = connect(SMALL)
    con.execute(f"CREATE OR REPLACE VIEW part AS SELECT * FROM '{d}/part.parquet/*.parquet'")
    for name in [f"meta_{x}_part" for x in (*meta.WEIGHTS, *meta.PRUNES, "broadcast")]:
        same(comparing.QUERIES[name](spark, d), con, comparing.ORACLE_SQL[name])


def test_quality_of_classes_lays_out_no_pair(spark):
    from rareblock.operators import metrics

    i = index(spark, {"A": {1, 2, 3, 4}, "B": {3, 4, 5}, "C": {6, 7}})
    truth = spark.createDataFrame([(1, 2), (3, 5), (4, 5), (1, 7)], "rid1 bigint, rid2 bigint")
    held = meta.classes(i)
    edge = meta.edges(meta.block_postings(held, purge=None))
    assert metrics.class_quality(edge, held, truth).first() == metrics.quality(baselines.all_pairs(i), truth).first() == (9, 3, 4, 0.75, round(3 / 9, 6))
    assert edge.count() == 5


def test_asked_pairs_are_those_of_the_rounds(spark):
    rng = random.Random(3)
    groups = [set(rng.sample(range(70), 30)) for _ in range(4)]
    blocks = {f"k{i}": set(rng.sample(sorted(rng.choice(groups)), rng.choice([2, 3, 12, 20, 26]))) for i in range(30)}
    blocks |= {"twin": blocks["k0"], "also": blocks["k0"], "all": set(range(70))}
    every = spark.createDataFrame(list(itertools.combinations(range(70), 2)), "rid1 bigint, rid2 bigint")
    for settings in ({"block_cap": 2}, {"block_cap": 3}, {"block_cap": 5, "key_cap": 5}, {"block_cap": 2, "shrink_ratio": 0.6}):
        cfg = BlockingConfig(counting="exact").but(**settings)
        run = rib.run(index(spark, blocks), cfg)
        wanted = {(r.rid1, r.rid2) for r in rib.pairs_of(run.blocks(), cfg).collect()}
        assert len(run.report) > 2 and 0 < len(wanted) < every.count()
        assert {tuple(r) for r in Asked(index(spark, blocks), cfg).of(every).collect()} == wanted


def test_matches_lay_out_no_candidates(spark, monkeypatch):
    def none(*_):
        raise AssertionError("candidates are laid out")

    monkeypatch.setattr(pair_ops, "expand", none)
    monkeypatch.setattr(pair_ops, "propagate", none)
    assert comparing.QUERIES["match_docs"](spark, SMALL).count() > 0


def test_class_edges_stand_for_the_pairs_of_records(spark, random_blocks):
    blocks = {name: {x for r in members for x in range(r * 4, r * 4 + 1 + r % 4)} for name, members in random_blocks.items()}
    every = index(spark, blocks)
    held = meta.classes(every)
    assert held.count() < every.count()
    for cap in (2, 6, 15):
        cfg = BlockingConfig(block_cap=cap, counting="exact")
        edge = rib.class_edges(held, cfg)
        assert {tuple(r) for r in meta.lay_out(edge, held).select("rid1", "rid2").collect()} == set(pairs(spark, blocks, block_cap=cap))


def test_sensitivity_lays_out_no_copies(spark, tmp_path, monkeypatch):
    from rareblock.workloads import fixtures as fx

    part = spark.read.parquet(f"{SMALL}/part.parquet")
    step = part.agg(F.max("p_partkey") + 1).first()[0]
    part.crossJoin(spark.range(50)).withColumn("p_partkey", F.col("p_partkey") + F.col("id") * step).drop("id").write.parquet(f"{tmp_path}/part.parquet")
    sizes = []
    monkeypatch.setattr(rib, "run", lambda index, cfg, run=rib.run: (sizes.append(index.count()), run(index, cfg))[1])
    monkeypatch.setattr(comparing, "SETTINGS", (("block_cap", 40), ("block_cap", 2000)))
    few, all_ = comparing.QUERIES["sensitivity_part"](spark, str(tmp_path)).collect()
    truth = fx.part_truth(spark, str(tmp_path)).count()
    assert max(sizes) <= part.count()
    assert (few.pairs, few.pc) == (0, 0.0) and all_.pairs >= truth > 0 and all_.pc == 1.0 and all_.pq == round(truth / all_.pairs, 6)
