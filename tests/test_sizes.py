"""What queries must not do as tables grow, and their results on odd rows."""

from conftest import MEDIUM, SMALL
from pyspark.sql import functions as F

from rareblock.functions import minhash, text
from rareblock.workloads import building, relational


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_self_join_is_counted(spark):
    assert "Join" not in _plan(relational.QUERIES["join_self_key"](spark, MEDIUM))


def test_bands_come_from_arrays(spark):
    made = building.QUERIES["lsh_docs_10_6"](spark, SMALL)
    assert "ArrowEvalPython" in _plan(made) and _plan(made).count("ArrowEvalPython") == 1
    slow = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", F.explode(minhash.band_texts(minhash.signature(text.words(F.col("text")), 60), 10, 6, "text")).alias("t"))
    want = slow.select("doc_id", F.md5(F.col("t").cast("binary")).alias("key"))
    assert made.select("doc_id", "key").exceptAll(want).count() == 0 and made.count() == want.count()


def test_similarity_join_loses_no_pair(spark, monkeypatch):
    """Against all pairs, with few known counts, records of both widths of parities, and copies."""
    import random

    from rareblock.operators import simjoin

    draw = random.Random(1)
    monkeypatch.setattr(simjoin, "LARGE", 12)
    monkeypatch.setattr(simjoin.prefixes, "__defaults__", (5,))
    rows = []
    for i in range(150):
        w = [draw.choice("abcdefghijklmnopqrstuvwxyz") + str(draw.randrange(2)) for _ in range(draw.randrange(1, 25))]
        rows += [(i, " ".join(w)), (1000 + i, " ".join(w[i % 3 :]))]
    sets = {i: set(t.split()) for i, t in rows if t}
    alike = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a in sets for b in sets if a < b}
    df = spark.createDataFrame([*rows, (5000, None), (None, "a0 b1")], "id bigint, text string")
    for least in (0.3, 0.8, 1.0):
        got = {(r[0], r[1]): r[2] for r in simjoin.jaccard_join(df, "id", text.words(F.col("text")), least).collect()}
        assert got == {p: j for p, j in alike.items() if j >= least - 1e-12}


def test_similarity_join_drops_unlike_pairs_early(spark):
    """Records that share only their rarest token are no rows beyond the task that meets them."""
    from rareblock.operators import simjoin

    df = spark.createDataFrame([(i, ["rare"] + [f"w{i}_{k}" for k in range(40)]) for i in range(200)], "rid bigint, t array<string>")
    few = simjoin.prefixes(df.select("rid", F.transform("t", lambda t: F.xxhash64(t)).alias("h")), 0.8, 0)
    assert simjoin._met(few, 0.8).count() == 0


def test_formulas_read_tables(spark):
    from rareblock.workloads import comparing, method

    for module, name in ((method, "bit_index_grid"), (comparing, "cost_model"), (comparing, "scaling_fit"), (building, "lsh_curve")):
        made = module.QUERIES[name](spark, SMALL)
        assert made.inputFiles() and made.count(), name
