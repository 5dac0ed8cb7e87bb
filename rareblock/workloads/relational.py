"""Relational operators, functions and windows that users of the method need around it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text
from ..functions.hashing import printed
from ..operators import baselines, joins, keys, rib, rounds
from ..operators.simjoin import jaccard_join
from ..sources.tables import IDS, LINEITEM_KEY, load
from ..streaming import windows
from . import fixtures as fx
from . import sql


def _scan(name: str, column: str):
    return lambda s, d: load(s, d, name).agg(F.count("*").alias("n"), F.min(column).cast("bigint").alias("lo"), F.max(column).cast("bigint").alias("hi"))


def _part_pairs(s, d: str) -> DataFrame:
    return rib.pairs_of(rib.run(fx.part_index(s, d), fx.config("part")).blocks(), fx.config("part"))


def _nations(hint: str):
    def query(s, d: str) -> DataFrame:
        n, r = load(s, d, "nation"), load(s, d, "region")
        joined = load(s, d, "customer").join(n.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).join(r.hint(hint), F.col("n_regionkey") == F.col("r_regionkey"))
        return joined.groupBy("r_name", "n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))

    return query


def _full(s, d: str) -> DataFrame:
    side = lambda t, p: load(s, d, t).groupBy(F.col(f"{p}_nationkey").alias("nation")).agg(F.count("*").alias(t)).filter(F.col(t) % 2 == 0)
    return side("supplier", "s").join(side("customer", "c"), "nation", "full").select(F.col("nation").cast("bigint").alias("nation"), "supplier", "customer")


def _marks(how: str):
    def query(s, d: str) -> DataFrame:
        a, b = _part_pairs(s, d).select("rid1", "rid2"), fx.part_truth(s, d)
        return a.join(b, ["rid1", "rid2"], "left_semi") if how == "semi" else b.join(a, ["rid1", "rid2"], "left_anti")

    return query


def _theta(s, d: str) -> DataFrame:
    b = load(s, d, "benchmark").select(F.col("item_id").alias("i"), text.words(F.col("text")).alias("w"))
    both = b.alias("a").join(b.alias("b"), F.col("a.i") < F.col("b.i"))
    return both.select(F.col("a.i").alias("item1"), F.col("b.i").alias("item2"), F.round(text.jaccard(F.col("a.w"), F.col("b.w")), 6).alias("j")).filter("j >= 0.1")


def _self_joined(s, d: str) -> DataFrame:
    """Rows of the index's self join per key, one per pair: counted, as the join grows with the square of a block."""
    sizes = rounds.key_stats(keys.postings(keys.build_index(fx.part(s, d), "p_partkey", [keys.identity("p_brand")])))
    return sizes.filter("size > 1").select(printed(F.col("key")).alias("key"), F.expr("size * (size - 1) div 2").alias("pairs"))


def _histogram(s, d: str) -> DataFrame:
    sizes = keys.postings(fx.orders_index(s, d)).groupBy("key").agg(F.count("*").alias("size"))
    return sizes.groupBy("size").agg(F.count("*").alias("blocks"))


def _grouped(how: str):
    def query(s, d: str) -> DataFrame:
        docs = fx.docs(s, d)
        if how == "gsets":
            docs.createOrReplaceTempView("rb_documents")
            return s.sql("SELECT lang, source, count(*) AS n FROM rb_documents GROUP BY GROUPING SETS ((lang), (source), ())")
        return getattr(docs, how)("lang", "source").agg(F.count("*").alias("n"))

    return query


def _small_blocks(s, d: str) -> DataFrame:
    sized = keys.postings(fx.part_index(s, d)).withColumn("size", F.count("*").over(Window.partitionBy("key")))
    nth = F.row_number().over(Window.partitionBy("rid").orderBy("size", "key"))
    return sized.withColumn("nth", nth).filter("nth <= 3").select("rid", printed(F.col("key")).alias("key"), "size", F.col("nth").cast("bigint").alias("nth"))


def _by_customer(*order):
    return Window.partitionBy("o_custkey").orderBy(*order)


def _both_pairs(s, d: str) -> tuple[DataFrame, DataFrame]:
    return _part_pairs(s, d).select("rid1", "rid2"), baselines.cap_drop(fx.part_index(s, d), fx.CAPS["part"])


def _exists(s, d: str) -> DataFrame:
    docs = fx.docs(s, d).select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    return docs.alias("a").join(docs.alias("b"), (F.col("a.h") == F.col("b.h")) & (F.col("a.doc_id") != F.col("b.doc_id")), "left_semi").select("doc_id")


_orders = lambda s, d: load(s, d, "orders")
_events = lambda s, d: load(s, d, "events")

QUERIES = {
    "filter_docs": lambda s, d: fx.docs(s, d).filter(F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 1000) & F.col("text").rlike("[0-9]")).select("doc_id"),
    "project_orders": lambda s, d: _orders(s, d).select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m")),
    "case_priority": lambda s, d: _orders(s, d).groupBy(F.when(F.col("o_totalprice") < 100000, "low").when(F.col("o_totalprice") < 300000, "middle").otherwise("high").alias("band")).agg(F.count("*").alias("n")),
    "join_hash": _nations("shuffle_hash"),
    "join_bcast": _nations("broadcast"),
    "join_smj": _nations("merge"),
    "join_left": lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels"), "doc_id", "left").select("doc_id", F.col("quality").cast("bigint").alias("quality")),
    "join_full": _full,
    "semi_pairs": _marks("semi"),
    "anti_missed": _marks("anti"),
    "theta_bruteforce": _theta,
    "jaccard_join_benchmark": lambda s, d: jaccard_join(load(s, d, "benchmark"), "item_id", text.words(F.col("text")), 0.1).select(F.col("rid1").alias("item1"), F.col("rid2").alias("item2"), F.round("jaccard", 6).alias("j")),
    "join_range": lambda s, d: joins.band_join(fx.part(s, d), "p_partkey", F.col("p_size"), 1, ["p_brand"]),
    "join_interval": lambda s, d: joins.band_join(_orders(s, d), "o_orderkey", F.unix_timestamp(F.col("o_orderdate").cast("timestamp")), 86400, ["o_custkey"]),
    "join_asof": lambda s, d: _events(s, d).select("event_id", joins.as_of(_events(s, d), "user_id", ["ts", "event_id"], F.when(F.col("event_type") == "error", F.col("event_id"))).alias("error_id")),
    "join_self_key": _self_joined,
    "agg_hist": _histogram,
    "agg_distinct": lambda s, d: _orders(s, d).agg(*[F.count_distinct(c).alias(c) for c in ("o_custkey", "o_orderstatus", "o_orderpriority")]),
    "agg_xor": lambda s, d: _orders(s, d).groupBy("o_orderstatus").agg(F.bit_xor("o_orderkey").alias("x"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest")),
    "agg_cube": _grouped("cube"),
    "agg_rollup": _grouped("rollup"),
    "agg_gsets": _grouped("gsets"),
    "agg_pivot": lambda s, d: _orders(s, d).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0),
    "win_rank": _small_blocks,
    "win_lag": lambda s, d: _orders(s, d).select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(_by_customer("o_orderdate", "o_orderkey"))).cast("bigint").alias("gap")),
    "win_frame": lambda s, d: _orders(s, d).select("o_orderkey", F.round(F.sum("o_totalprice").over(_by_customer("o_orderdate", "o_orderkey").rowsBetween(-2, 0)), 2).alias("three")),
    "win_range": lambda s, d: _orders(s, d).withColumn("day", F.datediff("o_orderdate", F.lit("1990-01-01").cast("date"))).select("o_orderkey", F.count("*").over(_by_customer("day").rangeBetween(-6, 0)).alias("week")),
    "win_ntile": lambda s, d: fx.part(s, d).select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("bigint").alias("quarter"), F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).cast("bigint").alias("dense")),
    "topk_blocks": lambda s, d: keys.postings(fx.orders_index(s, d)).groupBy(printed(F.col("key")).alias("key")).agg(F.count("*").alias("size")).orderBy(F.desc("size"), "key").limit(10),
    "sort_pairs": lambda s, d: _part_pairs(s, d).orderBy(F.desc("size"), "rid1", "rid2").select("rid1", "rid2", "size"),
    "topk_group": lambda s, d: _part_pairs(s, d).withColumn("nth", F.row_number().over(Window.partitionBy("rid1").orderBy(F.desc("size"), "rid2"))).filter("nth <= 2").select("rid1", "rid2", "size"),
    "set_union": lambda s, d: (lambda a, b: a.union(b).distinct())(*_both_pairs(s, d)),
    "set_intersect": lambda s, d: (lambda a, b: a.intersect(b))(*_both_pairs(s, d)),
    "set_except": lambda s, d: (lambda a, b: a.exceptAll(b))(*_both_pairs(s, d)),
    "sub_exists": _exists,
    "sub_in": lambda s, d: _orders(s, d).join(load(s, d, "customer").filter(F.col("c_nationkey").isin(1, 2, 3)).select(F.col("c_custkey").alias("o_custkey")), "o_custkey", "left_semi").select("o_orderkey"),
    "sub_scalar": lambda s, d: _orders(s, d).crossJoin(F.broadcast(_orders(s, d).agg(F.avg("o_totalprice").alias("mean")))).filter("o_totalprice > mean").select("o_orderkey"),  # one row
    "hash_sample": lambda s, d: fx.docs(s, d).filter(F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 7), 16, 10).cast("bigint") % 10 == 0).select("doc_id"),
    "rid_lineitem": lambda s, d: fx.lineitem(s, d).select("rid", *LINEITEM_KEY[:4]),
    "fn_soundex": lambda s, d: fx.part(s, d).select("p_partkey", F.soundex(F.element_at(F.split("p_name", " "), 1)).alias("sound")),
    "fn_string": lambda s, d: fx.part(s, d).select("p_partkey", F.levenshtein("p_name", "p_type").cast("bigint").alias("edits"), F.sha2("p_brand", 256).alias("sha"), F.translate("p_brand", "#", "-").alias("plain"), F.concat_ws("/", "p_name", "p_type").alias("path")),
    "fn_html": lambda s, d: load(s, d, "pages").select("page_id", F.md5(fx.page_text().cast("binary")).alias("text_md5"), F.length(fx.page_text()).cast("bigint").alias("n")),
    "fn_url": lambda s, d: load(s, d, "pages").select("page_id", text.canonical_url(F.col("url")).alias("url")),
    "fn_date": lambda s, d: _orders(s, d).select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.datediff(F.lit("2000-01-01").cast("date"), "o_orderdate").cast("bigint").alias("left")),
    "fn_math": lambda s, d: fx.part(s, d).select("p_partkey", F.round(F.pow(F.col("p_size").cast("double"), 2) + F.log(F.col("p_retailprice")), 6).alias("m"), F.floor(F.col("p_retailprice") / 7).cast("bigint").alias("f"), F.shiftleft(F.col("p_size").cast("bigint"), 3).alias("s"), F.pmod(F.col("p_partkey") - 100, F.lit(7)).cast("bigint").alias("p")),
    "fn_array": lambda s, d: fx.part(s, d).select("p_partkey", F.array_join(F.array_sort(F.array_union(F.split("p_name", " "), F.split("p_type", " "))), ",").alias("u"), F.size(F.filter(F.split("p_name", " "), lambda x: F.length(x) > 3)).cast("bigint").alias("n"), F.aggregate(F.sequence(F.lit(1), F.col("p_size")), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("sum")),
    "fn_map": lambda s, d: _events(s, d).groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("event_type", F.length("event_type").alias("n"))))).alias("m")).select("user_id", F.array_join(F.array_sort(F.map_keys(F.map_filter("m", lambda k, v: v > 4))), ",").alias("long")),
    "fn_json": lambda s, d: _events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("bigint").alias("k")),
    "st_tumbling": lambda s, d: windows.tumbling(_events(s, d)).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss")),
    "st_sliding": lambda s, d: windows.sliding(_events(s, d)).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss")),
    "st_session": lambda s, d: windows.sessions(_events(s, d)).select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n"),
    "st_interval_join": lambda s, d: windows.follow_ups(_events(s, d)),
}

_nations_sql = "SELECT r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2"
_PAIRS = f"WITH {sql.rounds(sql.PART, 20, 2)}"
_TWO = f"{_PAIRS}, {sql.cap_drop(sql.PART, 20)}"
_theta_sql = f"SELECT item1, item2, round(j, 6) AS j FROM (SELECT a.item_id AS item1, b.item_id AS item2, len(list_intersect(a.w, b.w)) / CAST(len(a.w) + len(b.w) - len(list_intersect(a.w, b.w)) AS DOUBLE) AS j FROM (SELECT item_id, {sql.words('text')} AS w FROM benchmark) a JOIN (SELECT item_id, {sql.words('text')} AS w FROM benchmark) b ON a.item_id < b.item_id) WHERE round(j, 6) >= 0.1"
_per_user = "OVER (PARTITION BY user_id ORDER BY ts, event_id"
_per_customer = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"

ORACLE_SQL = {
    "filter_docs": "SELECT doc_id FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 1000 AND regexp_matches(text, '[0-9]')",
    "project_orders": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders",
    "case_priority": "SELECT CASE WHEN o_totalprice < 100000 THEN 'low' WHEN o_totalprice < 300000 THEN 'middle' ELSE 'high' END AS band, count(*) AS n FROM orders GROUP BY 1",
    "join_hash": _nations_sql, "join_bcast": _nations_sql, "join_smj": _nations_sql,
    "join_left": "SELECT doc_id, CAST(quality AS BIGINT) AS quality FROM documents LEFT JOIN labels USING (doc_id)",
    "join_full": "SELECT CAST(coalesce(s.k, c.k) AS BIGINT) AS nation, supplier, customer FROM (SELECT s_nationkey AS k, count(*) AS supplier FROM supplier GROUP BY 1 HAVING count(*) % 2 = 0) s FULL JOIN (SELECT c_nationkey AS k, count(*) AS customer FROM customer GROUP BY 1 HAVING count(*) % 2 = 0) c ON s.k = c.k",
    "semi_pairs": f"{_PAIRS} SELECT rid1, rid2 FROM pairs JOIN ({sql.PART_TRUTH}) USING (rid1, rid2)",
    "anti_missed": f"{_PAIRS} SELECT rid1, rid2 FROM ({sql.PART_TRUTH}) EXCEPT SELECT rid1, rid2 FROM pairs",
    "theta_bruteforce": _theta_sql,
    "jaccard_join_benchmark": _theta_sql,
    "join_range": "SELECT a.p_partkey AS rid1, b.p_partkey AS rid2 FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND abs(a.p_size - b.p_size) <= 1",
    "join_interval": "SELECT a.o_orderkey AS rid1, b.o_orderkey AS rid2 FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey AND abs(epoch(a.o_orderdate) - epoch(b.o_orderdate)) <= 86400",
    "join_asof": f"SELECT event_id, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) {_per_user} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS error_id FROM events",
    "join_self_key": f"SELECT key, n * (n - 1) // 2 AS pairs FROM (SELECT {sql.identity('p_brand', 'p_brand')} AS key, count(*) AS n FROM part GROUP BY 1) WHERE n > 1",
    "agg_hist": f"SELECT size, count(*) AS blocks FROM (SELECT count(*) AS size FROM ({sql.ORDERS}) GROUP BY key) GROUP BY size",
    "agg_distinct": "SELECT count(DISTINCT o_custkey) AS o_custkey, count(DISTINCT o_orderstatus) AS o_orderstatus, count(DISTINCT o_orderpriority) AS o_orderpriority FROM orders",
    "agg_xor": "SELECT o_orderstatus, bit_xor(o_orderkey) AS x, (array_agg(o_orderkey ORDER BY o_totalprice DESC, o_orderkey DESC))[1] AS dearest FROM orders GROUP BY 1",
    "agg_cube": "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)",
    "agg_rollup": "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)",
    "agg_gsets": "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "agg_pivot": "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1",
    "win_rank": f"SELECT rid, key, size, nth FROM (SELECT *, row_number() OVER (PARTITION BY rid ORDER BY size, key) AS nth FROM (SELECT rid, key, count(*) OVER (PARTITION BY key) AS size FROM ({sql.PART}))) WHERE nth <= 3",
    "win_lag": f"SELECT o_orderkey, date_diff('day', lag(o_orderdate) {_per_customer}), o_orderdate) AS gap FROM orders",
    "win_frame": f"SELECT o_orderkey, round(sum(o_totalprice) {_per_customer} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS three FROM orders",
    "win_range": "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1990-01-01', o_orderdate) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS week FROM orders",
    "win_ntile": "SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS quarter, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dense FROM part",
    "topk_blocks": f"SELECT key, count(*) AS size FROM ({sql.ORDERS}) GROUP BY key ORDER BY size DESC, key LIMIT 10",
    "sort_pairs": f"{_PAIRS} SELECT rid1, rid2, size FROM pairs ORDER BY size DESC, rid1, rid2",
    "topk_group": f"{_PAIRS} SELECT rid1, rid2, size FROM (SELECT *, row_number() OVER (PARTITION BY rid1 ORDER BY size DESC, rid2) AS best FROM pairs) WHERE best <= 2",
    "set_union": f"{_TWO} SELECT rid1, rid2 FROM pairs UNION SELECT * FROM capped",
    "set_intersect": f"{_TWO} SELECT rid1, rid2 FROM pairs INTERSECT SELECT * FROM capped",
    "set_except": f"{_TWO} SELECT rid1, rid2 FROM pairs EXCEPT SELECT * FROM capped",
    "sub_exists": "SELECT doc_id FROM documents a WHERE EXISTS (SELECT 1 FROM documents b WHERE b.text = a.text AND b.doc_id <> a.doc_id)",
    "sub_in": "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey IN (1, 2, 3))",
    "sub_scalar": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)",
    "hash_sample": "SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 7) AS BIGINT) % 10 = 0",
    "rid_lineitem": f"SELECT rid, {', '.join(LINEITEM_KEY[:4])} FROM {sql.LINE_ROWS}",
    "fn_string": "SELECT p_partkey, levenshtein(p_name, p_type) AS edits, sha256(p_brand) AS sha, translate(p_brand, '#', '-') AS plain, concat_ws('/', p_name, p_type) AS path FROM part",
    "fn_html": f"SELECT page_id, md5({sql.STRIPPED}) AS text_md5, CAST(length({sql.STRIPPED}) AS BIGINT) AS n FROM pages",
    "fn_url": "SELECT page_id, regexp_replace(regexp_replace(regexp_replace(lower(url), '[?#].*$', ''), '^[a-z]+://(www\\.)?', ''), '/+$', '') AS url FROM pages",
    "fn_date": "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m-%d') AS day, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, date_diff('day', o_orderdate, DATE '2000-01-01') AS \"left\" FROM orders",
    "fn_math": "SELECT p_partkey, round(pow(CAST(p_size AS DOUBLE), 2) + ln(p_retailprice), 6) AS m, CAST(floor(p_retailprice / 7) AS BIGINT) AS f, CAST(p_size AS BIGINT) << 3 AS s, ((p_partkey - 100) % 7 + 7) % 7 AS p FROM part",
    "fn_array": "SELECT p_partkey, array_to_string(list_sort(list_distinct(list_concat(string_split(p_name, ' '), string_split(p_type, ' ')))), ',') AS u, len(list_filter(string_split(p_name, ' '), lambda x: length(x) > 3)) AS n, CAST(p_size * (p_size + 1) // 2 AS BIGINT) AS sum FROM part",
    "fn_map": "SELECT user_id, coalesce(string_agg(DISTINCT event_type, ',' ORDER BY event_type) FILTER (WHERE length(event_type) > 4), '') AS long FROM events GROUP BY user_id",
    "fn_json": "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events",
    "st_tumbling": "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "st_sliding": "SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE FOR i IN range(0, 4)]) AS w FROM events) GROUP BY 1, 2",
    "st_session": f"SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) {_per_user}) AS nth FROM (SELECT *, CASE WHEN ts < lag(ts) {_per_user}) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, nth",
    "st_interval_join": "SELECT a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
}

for _t, _c in IDS.items():
    QUERIES[f"scan_{_t}"] = _scan(_t, _c)
    ORACLE_SQL[f"scan_{_t}"] = f"SELECT count(*) AS n, CAST(min({_c}) AS BIGINT) AS lo, CAST(max({_c}) AS BIGINT) AS hi FROM {_t}"
