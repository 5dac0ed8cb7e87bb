"""Pairs that are counted and not laid out."""

import random

import pytest
from conftest import MEDIUM
from oracle import connect, same

from rareblock.operators import counted, keys, metrics
from rareblock.workloads import comparing


def test_pairs_by_least_level(spark, monkeypatch):
    """Against sets of pairs: repeated ids, blocks of one record, true pairs of no block, and several runs of a sort."""
    monkeypatch.setattr(counted, "HELD", 50)
    draw = random.Random(3)
    blocks = [(draw.randrange(4), [draw.randrange(60) for _ in range(draw.randrange(1, 9))]) for _ in range(80)]
    true = sorted({tuple(sorted(draw.sample(range(70), 2))) for _ in range(90)})
    least = {}
    for level, rids in blocks:
        for p in {(a, b) for a in rids for b in rids if a < b}:
            least[p] = min(level, least.get(p, 99))
    found = counted.by_level(spark.createDataFrame(blocks, "level int, rids array<bigint>"), spark.createDataFrame(true, "rid1 bigint, rid2 bigint"))
    got = {r["level"]: (r["pairs"], r["hits"]) for r in found.collect() if r["pairs"] or r["hits"]}
    want = {lv: (sum(v == lv for v in least.values()), sum(least.get(p) == lv for p in true)) for lv in range(4)}
    assert got == want | {counted.TRUE: (0, sum(p not in least for p in true))}
    pairs = spark.createDataFrame([p for p, v in least.items() if v <= 2], "rid1 bigint, rid2 bigint")
    assert metrics.level_quality(found, 2).first() == metrics.quality(pairs, spark.createDataFrame(true, "rid1 bigint, rid2 bigint")).first()


def test_no_pairs(spark):
    none = spark.createDataFrame([], "rid1 bigint, rid2 bigint")
    found = counted.by_level(spark.createDataFrame([(0, [1])], "level int, rids array<bigint>"), none)
    assert metrics.level_quality(found, 0).first() == (0, 0, 0, 0.0, 0.0)


def test_token_keys_are_distinct(spark):
    df = spark.createDataFrame([(1, "a b a B"), (2, None)], "rid bigint, text string")
    made = keys.build_index(df, "rid", [keys.token(["text"])])
    assert [(r["rid"], len(r["keys"])) for r in made.collect()] == [(1, 2)]


@pytest.mark.parametrize("name", ["compare_at_point_docs"])
def test_comparisons_lay_out_no_pair(spark, monkeypatch, name):
    from rareblock.operators import baselines, pairs

    def refuse(*_):
        raise AssertionError("pairs are laid out")

    for module, made in ((pairs, "expand"), (pairs, "propagate"), (baselines, "all_pairs")):
        monkeypatch.setattr(module, made, refuse)
    same(comparing.QUERIES[name](spark, MEDIUM), connect(MEDIUM), comparing.ORACLE_SQL[name])


def test_halved_keys_are_counted(spark, monkeypatch):
    """The halved tokens' pairs are asked of no list of pairs: only banded and identity keys make one."""
    made = []
    monkeypatch.setattr(comparing, "_rib", lambda index, name, do=comparing._rib: made.append(name) or do(index, name))
    same(comparing.QUERIES["lsh_scatter_docs"](spark, MEDIUM), connect(MEDIUM), comparing.ORACLE_SQL["lsh_scatter_docs"])
    assert set(made) == {"lsh"}
