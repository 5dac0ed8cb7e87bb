"""Block building: keys, tokens, MinHash, banded keys, static keys."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import minhash, text
from ..functions.hashing import printed
from ..operators import baselines, keys
from ..operators.simjoin import jaccard_join
from ..sources.tables import load
from . import fixtures as fx
from . import sql


def _posted(index: DataFrame) -> DataFrame:
    return keys.postings(index).select("rid", printed(F.col("key")).alias("key"))


def _tokens(df: DataFrame, rid: str, tokens) -> DataFrame:
    return df.select(F.col(rid).alias("id"), F.explode(tokens).alias("token"))


def _banded(s, d: str, bands: int, width: int) -> DataFrame:
    signed = fx.docs(s, d).select("doc_id", minhash.fast_signature(text.words(F.col("text")), bands * width).alias("sig"))
    texts = signed.select("doc_id", F.posexplode(minhash.band_texts(F.col("sig"), bands, width, "text")).alias("band", "t"))
    return texts.select("doc_id", F.col("band").cast("bigint").alias("band"), F.md5(F.col("t").cast("binary")).alias("key"))


def _curve(s, d: str) -> DataFrame:
    """The chance that a document and its first half share a band, by their likeness in steps of a twentieth."""
    w = text.word_list(F.col("text"))
    half = fx.docs(s, d).select(F.size(F.array_distinct(F.slice(w, F.lit(1), F.ceil(F.size(w) / 2).cast("int")))).alias("a"), F.size(F.array_distinct(w)).alias("b"))
    steps = half.filter("b > 0").groupBy(F.floor(F.col("a") * 20 / F.col("b")).cast("bigint").alias("step")).agg(F.count("*").alias("docs"))
    got = minhash.curve(steps, [(1, 1), *minhash.LSH_GRID])
    return got.select(F.col("b").cast("bigint").alias("b"), F.col("w").cast("bigint").alias("w"), F.round("j", 2).alias("j"), "docs", F.round("prob", 6).alias("prob"))


def _empirical(s, d: str, bands: int = 6, width: int = 7) -> DataFrame:
    """Pairs of documents at least 0.3 alike, by tenths of similarity, and how many share a band."""
    pairs = jaccard_join(fx.docs(s, d), "doc_id", text.words(F.col("text")), 0.3)
    banded = fx.docs_lsh_index(s, d, bands, width)
    side = lambda n: banded.select(F.col("rid").alias(f"rid{n}"), F.col("keys").alias(f"k{n}"))
    met = pairs.join(side(1), "rid1").join(side(2), "rid2").select(F.floor(F.col("jaccard") * 10 + 1e-9).cast("bigint").alias("bin"), F.arrays_overlap("k1", "k2").alias("hit"))
    return met.groupBy("bin").agg(F.count("*").alias("pairs"), F.count_if("hit").alias("hits"))


def _two_columns(s, d: str) -> DataFrame:
    specs = [keys.lsh("text", "text", 3, 8), keys.identity(F.concat_ws("|", "source", "lang"), "source_lang")]
    return keys.build_index(fx.docs(s, d), "doc_id", specs).select(F.col("rid").alias("doc_id"), F.size("keys").cast("bigint").alias("n_keys"))


def _mixed(s, d: str) -> DataFrame:
    specs = [*fx.part_specs(), keys.lsh("p_name", "p_name_lsh", 6, 7, lambda c: text.qgrams(c, 3))]
    return keys.build_index(fx.part(s, d), "p_partkey", specs).select("rid", F.size("keys").cast("bigint").alias("n_keys"))


def _regrouped(s, d: str) -> DataFrame:
    long_df = keys.postings(fx.docs_index(s, d))
    back = keys.from_long(long_df, "rid", "key").withColumn("k", F.array_sort(F.transform("keys", printed)))
    return back.select("rid", F.size("k").cast("bigint").alias("n_keys"), F.md5(F.array_join("k", "").cast("binary")).alias("checksum"))


QUERIES = {
    "identity_part": lambda s, d: _posted(keys.build_index(fx.part(s, d), "p_partkey", [keys.identity("p_brand")])),
    "index_orders": lambda s, d: _posted(fx.orders_index(s, d)),
    "normalise_docs": lambda s, d: fx.docs(s, d).select("doc_id", F.md5(text.normalise(F.col("text")).cast("binary")).alias("norm_md5")),
    "token_docs": lambda s, d: _posted(fx.docs_index(s, d)),
    "token_two_attr": lambda s, d: _posted(keys.build_index(fx.part(s, d), "p_partkey", [keys.token(["p_name", "p_type"])])),
    "keys_from_long": _regrouped,
    "tok_words": lambda s, d: _tokens(fx.docs(s, d), "doc_id", text.words(F.col("text"))),
    "tok_ngrams": lambda s, d: _tokens(fx.docs(s, d), "doc_id", text.word_ngrams(F.col("text"), 2)),
    "tok_qgrams": lambda s, d: _tokens(fx.part(s, d), "p_partkey", text.qgrams(F.col("p_name"), 3)),
    "minhash_docs": lambda s, d: fx.docs(s, d).select("doc_id", F.posexplode(minhash.signature(text.words(F.col("text")), 24)).alias("i", "minhash")).select("doc_id", F.col("i").cast("bigint").alias("i"), "minhash"),
    "minhash_fast_docs": lambda s, d: fx.docs(s, d).select("doc_id", minhash.fast_signature(text.words(F.col("text")), 24).alias("sig")).select("doc_id", F.posexplode("sig").alias("i", "minhash")).select("doc_id", F.col("i").cast("bigint").alias("i"), "minhash"),
    "lsh_two_cols": _two_columns,
    "lsh_curve": _curve,
    "lsh_curve_empirical": _empirical,
    "mixed_part_docs": _mixed,
    "static_one_field": lambda s, d: baselines.static_pairs(load(s, d, "customer"), "c_custkey", ["c_nationkey"]),
    "static_two_fields": lambda s, d: baselines.static_pairs(load(s, d, "customer"), "c_custkey", ["c_nationkey", "c_mktsegment"]),
}

_ngrams = "SELECT DISTINCT doc_id AS id, w[i] || ' ' || w[i + 1] AS token FROM (SELECT doc_id, w, unnest(range(1, len(w))) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+') AS w FROM documents))"
_qgrams = "SELECT DISTINCT p_partkey AS {id}, substr(lower(p_name), i, 3) AS {t} FROM (SELECT p_partkey, p_name, unnest(range(1, length(p_name) - 1)) AS i FROM part)"
_minhash = f"SELECT rid AS doc_id, CAST(i AS BIGINT) AS i, mh AS minhash FROM ({sql.minima(sql.DOC_TOKENS, 24)})"
_static = "SELECT a.c_custkey AS rid1, b.c_custkey AS rid2 FROM customer a JOIN customer b USING ({0}) WHERE a.c_custkey < b.c_custkey"

ORACLE_SQL = {
    "identity_part": sql.index("part", "p_partkey", [("p_brand", "p_brand")]),
    "index_orders": sql.ORDERS,
    "normalise_docs": "SELECT doc_id, md5(trim(regexp_replace(lower(text), '\\s+', ' ', 'g'))) AS norm_md5 FROM documents",
    "token_docs": sql.DOCS,
    "token_two_attr": f"SELECT DISTINCT rid, md5(t) AS key FROM (SELECT p_partkey AS rid, unnest({sql.words('p_name')}) AS t FROM part UNION ALL SELECT p_partkey, unnest({sql.words('p_type')}) FROM part)",
    "keys_from_long": f"SELECT rid, count(*) AS n_keys, md5(string_agg(key, '' ORDER BY key)) AS checksum FROM ({sql.DOCS}) GROUP BY rid",
    "tok_words": "SELECT rid AS id, t AS token FROM (" + sql.DOC_TOKENS + ")",
    "tok_ngrams": _ngrams,
    "tok_qgrams": _qgrams.format(id="id", t="token"),
    "minhash_docs": _minhash,
    "minhash_fast_docs": _minhash,
    "lsh_two_cols": f"SELECT rid AS doc_id, count(DISTINCT key) AS n_keys FROM (SELECT rid, key FROM ({sql.lsh(sql.DOC_TOKENS, 'text', 3, 8)}) UNION ALL SELECT doc_id, {sql.identity('source_lang', chr(39).join(['source || ', '|', ' || lang']))} FROM documents) GROUP BY rid",
    "lsh_curve": "SELECT CAST(b AS BIGINT) AS b, CAST(w AS BIGINT) AS w, round(k / 20.0, 2) AS j, docs, round(1 - pow(1 - pow(k / 20.0, w), b), 6) AS prob FROM (VALUES (1,1),(3,8),(6,7),(10,6),(12,5),(14,4),(16,3)) AS g(b, w), "
    "(SELECT len(list_distinct(w[1:(len(w) + 1) // 2])) * 20 // len(list_distinct(w)) AS k, count(*) AS docs FROM (SELECT regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+') AS w FROM documents) WHERE len(w) > 0 GROUP BY 1)",
    "lsh_curve_empirical": f"WITH {sql.truth_docs(0.3)}, bk AS MATERIALIZED ({sql.docs_lsh(6, 7)}), met AS (SELECT DISTINCT a.rid AS rid1, b.rid AS rid2 FROM bk a JOIN bk b ON a.key = b.key AND a.rid < b.rid) "
    "SELECT CAST(floor(jaccard * 10 + 1e-9) AS BIGINT) AS bin, count(*) AS pairs, count(m.rid1) AS hits FROM tj LEFT JOIN met m ON m.rid1 = tj.rid1 AND m.rid2 = tj.rid2 WHERE jaccard >= 0.3 GROUP BY 1",
    "mixed_part_docs": f"SELECT rid, count(DISTINCT key) AS n_keys FROM ({sql.PART} UNION ALL SELECT rid, key FROM ({sql.lsh(_qgrams.format(id='rid', t='t'), 'p_name_lsh', 6, 7)})) GROUP BY rid",
    "static_one_field": _static.format("c_nationkey"),
    "static_two_fields": _static.format("c_nationkey, c_mktsegment"),
}

for _b, _w in minhash.LSH_GRID:
    QUERIES[f"lsh_docs_{_b}_{_w}"] = lambda s, d, b=_b, w=_w: _banded(s, d, b, w)
    ORACLE_SQL[f"lsh_docs_{_b}_{_w}"] = f"SELECT rid AS doc_id, CAST(band AS BIGINT) AS band, key FROM ({sql.lsh(sql.DOC_TOKENS, 'text', _b, _w)})"
