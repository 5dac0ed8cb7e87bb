"""The pipeline's stages, each on what the stage before kept."""

from conftest import MEDIUM, SMALL
from pyspark.sql import functions as F


import corpus_pipeline as pipeline
from rareblock.llm import decontamination, neardup, pseudonyms
from rareblock.llm.common import settle, table


def test_stages(spark, tmp_path):
    docs, kept = table(spark, MEDIUM, "documents"), []
    columns = docs.columns
    for name, stage in pipeline.STAGES:
        stage(spark, docs, MEDIUM).write.parquet(f"{tmp_path}/{name}")
        made = spark.read.parquet(f"{tmp_path}/{name}")
        if name != "packing":
            assert made.columns == columns
            kept.append({r[0] for r in made.select("doc_id").collect()})
            docs = made
    labels = table(spark, MEDIUM, "labels").join(table(spark, MEDIUM, "documents"), "doc_id")
    toxic = {r[0] for r in labels.filter("toxic = 1").select("doc_id").collect()}
    clean = {r[0] for r in labels.filter("toxic = 0").select("doc_id").collect()}
    # Fifty toxic texts teach few of the words; on the larger tables none is missed.
    assert len(toxic & kept[0]) <= 0.1 * len(toxic) and len(clean - kept[0]) <= 0.05 * len(clean)
    after = spark.read.parquet(f"{tmp_path}/near_duplicates")
    assert neardup.near_duplicates(after, 5, 80).filter("NOT kept").count() == 0
    leaks = decontamination.find_contamination(after, table(spark, MEDIUM, "benchmark")).filter("size(spans) > 0")
    assert kept[2] == kept[1] - {r[0] for r in leaks.select("doc_id").collect()}
    assert kept[3] == kept[2]
    private = spark.read.parquet(f"{tmp_path}/decontamination").filter(F.col("text").rlike(pseudonyms.PATTERNS["email"])).select("doc_id", F.regexp_extract("text", pseudonyms.PATTERNS["email"], 0).alias("m"))
    assert private.join(docs, "doc_id").filter(F.col("text").contains(F.col("m"))).count() == 0
    packed = made.groupBy("doc_id").agg(F.sum("length")).count()
    assert packed == len(kept[3])


def test_odd_rows(spark):
    """Nulls, empties, repeats, null ids and clashing columns go through every stage; what is kept keeps its columns."""
    texts = ["the same text here again and again, with some more words to it", "another one, jo@example.org and 4111 1111 1111 1111 in it", "", " \n", None, "long " * 20_000]
    rows = [(1, texts[0], "en"), (2, texts[0], "en"), (2, texts[0], "en"), (3, texts[1], None), (None, texts[1], "en"), (None, "no id", None), (4, texts[2], "a"), (5, texts[3], "b"), (6, None, None), (7, texts[5], "x"), (7, texts[5], "x")]
    docs = spark.createDataFrame([(i, t, x, None, None if t is None else len(t)) for i, t, x in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs = docs.withColumns({c: F.lit(c) for c in ("_private", "_values", "_typed", "_renamed", "_hit", "_gone", "length", "rank", "node", "size", "content", "again")})
    columns, seen = docs.columns, [docs.count()]
    for name, stage in pipeline.STAGES[:-1]:
        docs = settle(stage(spark, docs, SMALL), name)
        assert docs.columns == columns
        seen.append(docs.count())
    assert seen == [11, 11, 8, 8, 8]  # one of the copies of 1, 2 and 7 stays, and every row without an id
    kept = docs.collect()
    assert {r["doc_id"] for r in kept} == {1, 3, None, 4, 5, 6, 7} and all(r["_private"] == "_private" for r in kept)
    assert not [r for r in kept if r["text"] and "jo@" in r["text"]] and sum(r["text"] is None for r in kept) == 1
    packed = pipeline.STAGES[-1][1](spark, docs, SMALL)
    assert {r["doc_id"] for r in packed.select("doc_id").collect()} == {r["doc_id"] for r in kept}
    assert docs.filter("false").transform(lambda d: pipeline.STAGES[-1][1](spark, d, SMALL)).count() == 0


def test_groups_of_the_pipeline_against_brute_force(spark):
    """Links at 0.8 on five-word shingles, by plain sets over all documents; groups by spreading the least id."""
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in table(spark, MEDIUM, "documents").collect()}
    fold = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
    sets, where = {}, {}
    for i, t in texts.items():
        w = t.translate(fold).split()
        sets[i] = {tuple(w[a : a + 5]) for a in range(max(1, len(w) - 4))} if w else set()
        for s in sets[i]:
            where.setdefault(s, []).append(i)
    shared = {}
    for group in where.values():
        for n, a in enumerate(group):
            for b in group[:n]:
                shared[a, b] = shared.get((a, b), 0) + 1
    least = {i: i for i in texts}
    links = [(a, b) for (a, b), c in shared.items() if 100 * c >= 80 * (len(sets[a]) + len(sets[b]) - c)]
    changed = True
    while changed:
        changed = False
        for a, b in links:
            low = min(least[a], least[b])
            changed |= least[a] != low or least[b] != low
            least[a] = least[b] = low
    got = {r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(table(spark, MEDIUM, "documents"), 5, 80).collect()}
    assert got == least and sum(i != c for i, c in got.items()) > 50
