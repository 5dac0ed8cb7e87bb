"""Sources, sinks, SQL functions, streams, scoring, and the driver's entry points."""

from conftest import MEDIUM, SMALL
from pyspark.sql import functions as F

import __spark_entry__ as driver
from rareblock.config import BlockingConfig
from rareblock.functions import minhash, sqlapi, text
from rareblock.operators import keys, match, metrics, rib, rounds
from rareblock.sources import sinks, tables
from rareblock.streaming import incremental, windows


def test_entry(spark):
    got = driver.entry(spark)
    assert got.columns == ["rid1", "rid2", "key", "size"] and got.count() > 0
    assert set(driver.oracle_sql()) <= set(driver.queries())


def test_formats(spark, tmp_path):
    nation = tables.load(spark, SMALL, "nation")
    for fmt in ("csv", "json", "orc", "parquet"):
        sinks.write(nation, f"{tmp_path}/{fmt}", fmt=fmt)
        back = tables.read(spark, fmt, f"{tmp_path}/{fmt}", None if fmt in ("orc", "parquet") else "n_nationkey int, n_name string, n_regionkey int")
        assert back.exceptAll(nation).count() == 0 and back.count() == 25
    posts = keys.postings(keys.build_index(nation, "n_nationkey", [keys.identity("n_name")]))
    sinks.write(posts, f"{tmp_path}/posts", by="key_prefix")
    assert spark.read.parquet(f"{tmp_path}/posts").filter("key_prefix < '80'").count() <= 25


def test_sql_functions(spark):
    sqlapi.register(spark)
    row = spark.sql("SELECT rb_tokens('Foo bar foo') AS t, rb_qgrams('abcd', 3) AS q, rb_bit_index(0, 3, 4) AS b, round(rb_lsh_prob(6, 7, 0.8), 4) AS p, rb_jaccard(array('a', 'b'), array('b')) AS j").first()
    assert row["t"] == ["foo", "bar"] and row["q"] == ["abc", "bcd"] and row["b"] == 2 and row["p"] == 0.7564 and row["j"] == 0.5
    assert spark.sql("SELECT * FROM VALUES (array(5L, 3L, 9L)) AS b(r), LATERAL block_pairs(r)").count() == 3
    assert spark.sql("SELECT * FROM key_grid(3, 2)").count() == 6
    words = "the quick brown fox jumps over the lazy dog"
    banded = keys.build_index(spark.createDataFrame([(1, words)], "rid bigint, text string"), "rid", [keys.lsh("text", "text", 3, 2)]).first()
    same = spark.sql(f"SELECT rb_lsh_keys(rb_minhash(rb_tokens('{words}'), 6), 3, 2, 'text') AS k, rb_minhash(array(), 3) AS none").first()
    assert sorted(map(bytes, same["k"])) == sorted(map(bytes, banded["keys"])) and same["none"] is None


def test_fast_bands_are_the_same(spark):
    docs = tables.load(spark, SMALL, "documents").limit(50)
    made = [{r["rid"]: sorted(map(bytes, r["keys"])) for r in keys.build_index(docs, "doc_id", [keys.lsh("text", "text", 6, 7, fast=fast)]).collect()} for fast in (False, True, None)]
    assert made[0] == made[1] == made[2]


def test_lsh_numbers():
    assert [round(minhash.threshold(b, w), 3) for b, w in minhash.LSH_GRID] == [0.872, 0.774, 0.681, 0.608, 0.517, 0.397]
    b, w = minhash.pick(0.8, 48)
    assert abs(minhash.threshold(b, w) - 0.8) < 0.05
    assert round(metrics.scoring_days(1_400_000 * 1_399_999 // 2, 50)) == 567 and round(metrics.f1(0.5, 1.0), 3) == 0.667


def test_text(spark):
    row = spark.range(1).select(text.normalise(F.lit("  É  B "), strip_accents=True).alias("n"), text.strip_html(F.lit("<p>a &amp; b<script>x</script></p>")).alias("h"), text.canonical_url(F.lit("HTTP://www.A.com/x/?q#f")).alias("u"), text.word_ngrams(F.lit("a b"), 3).alias("g")).first()
    assert (row["n"], row["h"], row["u"], row["g"]) == ("e b", "a & b", "a.com/x", [])


def test_autospec(spark):
    part = tables.load(spark, SMALL, "part")
    names = [s.name for s in keys.autospec(part, "p_partkey")]
    assert len(names) == len(part.columns) - 1
    late = spark.createDataFrame([(i, None if i < 1500 else "a text of many words") for i in range(3000)], "rid bigint, text string")
    assert [s.name for s in keys.autospec(late, "rid")] == ["lsh(text,6,7)"]


def test_shared_folder(spark):
    from types import SimpleNamespace

    import pytest

    from rareblock.plans import storage

    conf = SimpleNamespace(get=lambda key, default=None: default)
    cluster = SimpleNamespace(sparkContext=SimpleNamespace(master="yarn", getConf=lambda: conf, getCheckpointDir=lambda: None))
    with pytest.raises(RuntimeError):
        storage.shared_dir(cluster)


def test_operators_of_texts_can_go(tmp_path):
    """Without the folders of the training-data operators, and only then, the other queries stay alone."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(driver.__file__).parent
    for name in ("rareblock", "__spark_entry__.py", "corpus_pipeline.py"):
        if (root / name).exists():
            (shutil.copytree if (root / name).is_dir() else shutil.copy)(root / name, tmp_path / name)
    ask = [sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), any(q.startswith('op') for q in e.queries()))"]
    run = lambda: subprocess.run(ask, cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
    if (root / "rareblock" / "llm").is_dir() and (root / "corpus_pipeline.py").exists():
        module = tmp_path / "rareblock" / "llm" / "packing.py"
        text = module.read_text()
        module.write_text("import a_module_that_is_not_there\n" + text)
        assert run().returncode != 0  # a broken operator is not silently left out
        module.write_text(text)
    shutil.rmtree(tmp_path / "rareblock" / "llm", ignore_errors=True)
    (tmp_path / "corpus_pipeline.py").unlink(missing_ok=True)
    alone = run()
    assert alone.returncode == 0 and alone.stdout.split()[1] == "False", alone.stderr


def test_streams_equal_batches(spark, tmp_path):
    events = tables.load(spark, SMALL, "events")
    events.repartition(4).write.parquet(f"{tmp_path}/in")
    source = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    q = windows.tumbling(source(), late="60 days").writeStream.format("memory").queryName("tumbled").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    batch = windows.tumbling(events).withColumn("start", F.col("start").cast("timestamp"))
    assert spark.table("tumbled").exceptAll(batch).count() == 0 and spark.table("tumbled").count() == batch.count()
    state = incremental.IncrementalKeys(f"{tmp_path}/state", "event_id", [keys.identity("event_type"), keys.identity("user_id")])
    q = source().writeStream.foreachBatch(state.absorb).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    whole = rounds.key_stats(keys.postings(keys.build_index(events, "event_id", state.specs))).select("key", "size", "fp")
    assert state.stats(spark).exceptAll(whole).count() == 0 and whole.count() == state.stats(spark).count()
    assert state.over(spark, 100).count() == whole.filter("size > 100").count()
    fit, over = state.split(spark, 100)
    assert fit.count() + over.count() == whole.agg(F.sum("size")).first()[0] and over.select("key").distinct().count() == state.over(spark, 100).count()
    moved = [state.moved(spark, 100, b) for b in range(4)]
    batches = [r["batch"] for r in spark.read.parquet(f"{tmp_path}/state/stats").select("batch").distinct().collect()]
    assert sorted(batches) == [0, 1, 2, 3] and moved[0].count() == 0
    assert sum(m.select("key").distinct().count() for m in moved) + spark.read.parquet(f"{tmp_path}/state/stats").filter("batch = 0 AND size > 100").count() <= state.over(spark, 100).count()


def test_block_scoring(spark):
    part = tables.load(spark, MEDIUM, "part")
    packed = rib.candidate_blocks(part, "p_partkey", [keys.identity("p_name"), keys.identity("p_brand")], BlockingConfig(block_cap=20, counting="exact"))
    got = match.score_blocks(packed, part, "p_partkey", "p_type", lambda a, b: float(a == b), 1.0)
    pairs = rib.candidate_pairs(part, "p_partkey", [keys.identity("p_name"), keys.identity("p_brand")], BlockingConfig(block_cap=20, counting="exact"))
    want = match.score(pairs, part, "p_partkey", {"t": F.col("p_type")}, (F.col("t1") == F.col("t2")).cast("double"), 1.0)
    assert got.select("rid1", "rid2").exceptAll(want.select("rid1", "rid2")).count() == 0 and got.count() == want.count()
