"""Baselines, measures and the comparisons of the experiments."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import BlockingConfig
from ..functions import minhash, text
from ..functions.hashing import printed
from ..operators import baselines, counted, keys, match, meta, metrics, rib, rounds
from ..operators.asked import Asked
from ..operators.simjoin import hashes, jaccard_join
from ..plans.storage import collect, settle_alone
from ..sources.tables import load
from . import fixtures as fx
from . import sql

#: Microseconds of a comparison, machines of a run and their dollars an hour, as published.
MICROSECONDS, NODES, USD_PER_HOUR = 50, 100, 1.04

_INDEX = {"part": fx.part_index, "orders": fx.orders_index, "customer": fx.customer_index, "docs": fx.docs_index, "voter": fx.voter_index}
_TRUTH = {"part": fx.part_truth, "docs": fx.docs_truth, "voter": fx.voter_truth}


def _rib(index: DataFrame, name: str) -> DataFrame:
    return rib.pairs_of(rib.run(index, fx.config(name)).blocks(), fx.config(name)).select("rid1", "rid2")


def _indexed(s, d: str, name: str) -> tuple[DataFrame, DataFrame, BlockingConfig]:
    """A set's index and true pairs, written, and its settings. Documents' words are hashed once for both, to 64 bits."""
    if name != "docs":
        return rib.settle(_INDEX[name](s, d), "index"), rib.settle(_TRUTH[name](s, d).select("rid1", "rid2"), "truth"), fx.config(name)
    words = text.words(F.col("text"))
    hashed = hashes(fx.docs(s, d), "doc_id", words)
    truth = settle_alone(s, lambda: jaccard_join(fx.docs(s, d), "doc_id", words, 0.8, hashed).select("rid1", "rid2"), "truth")
    return hashed.select("rid", F.col("h").alias("keys")).filter("rid IS NOT NULL AND size(keys) > 0"), truth, fx.config(name, hash="h64")


def _blocks(index: DataFrame, cfg: BlockingConfig) -> DataFrame:
    """The method's blocks over a written index, all of one level."""
    made = rib.run(index, cfg, written=True).postings
    collect(made.sparkSession)
    held = made.repartition("key").groupBy("key").agg(F.collect_list("rid").alias("rids"))  # no list is sent, only postings
    return held.filter("size(rids) > 1").select(F.lit(0).alias("level"), "rids")


def _levels(blocks: Callable[[], DataFrame], truth: DataFrame) -> DataFrame:
    """counted.by_level() as a written table, of which alone files are left."""
    return settle_alone(truth.sparkSession, lambda: counted.by_level(blocks(), truth), "levels")


def _three(s, d: str, name: str) -> tuple[dict[str, DataFrame], DataFrame]:
    """Pairs of each method, MetaGraph's as edges between classes, and the classes."""
    index = rib.settle(_INDEX[name](s, d), "index")
    held = meta.classes(index)
    kept = meta.above_bars(meta.edges(meta.block_postings(held, purge=None)), "wnp")
    return {"CapDrop": baselines.cap_drop(index, fx.CAPS[name]), "MetaGraph": kept, "RIB": _rib(index, name)}, held


def _counted(pairs: DataFrame) -> DataFrame:
    """pairs: how many pairs of records, of pairs or of edges between classes."""
    return pairs.agg((F.coalesce(F.sum(F.expr(meta.PAIRS)), F.lit(0)) if "n1" in pairs.columns else F.count("*")).alias("pairs"))


def _stacked(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def _compared(name: str):
    def query(s, d: str) -> DataFrame:
        truth = rib.settle(_TRUTH[name](s, d).select("rid1", "rid2"), "truth")
        made, held = _three(s, d, name)
        measured = lambda p: metrics.class_quality(p, held, truth) if "n1" in p.columns else metrics.quality(p, truth)
        return _stacked([measured(p).select(F.lit(m).alias("method"), "pairs", "pc", "pq") for m, p in made.items()])

    return query


#: Multiples of a set's cap that the baseline is tried at, to meet the main method's number of pairs.
POINTS = (0.25, 0.5, 1, 1.5, 2, 4)


def _at_point(name: str):
    """The main method, and the threshold baseline at the cap whose number of pairs comes nearest to its."""

    def query(s, d: str) -> DataFrame:
        index, truth, cfg = _indexed(s, d, name)
        caps = [int(fx.CAPS[name] * x) for x in POINTS]
        ours = _levels(lambda: _blocks(index, cfg), truth)
        tried = _levels(lambda: counted.capped(index, caps), truth)
        pairs = {r["level"]: r["pairs"] for r in tried.collect()}  # a row per cap
        best = metrics.nearest({c: sum(pairs.get(i, 0) for i in range(k + 1)) for k, c in enumerate(caps)}, ours.agg(F.sum("pairs")).first()[0] or 0)
        rows = (("RIB", fx.CAPS[name], ours, 0), ("CapDrop", best, tried, caps.index(best)))
        return _stacked([metrics.level_quality(p, k).select(F.lit(m).alias("method"), F.lit(c).cast("bigint").alias("cap"), "pairs", "pc", "pq") for m, c, p, k in rows])

    return query


#: One setting changed at a time from cap 20, key cap 80, ratio 0.9.
SETTINGS = (("block_cap", 10), ("block_cap", 20), ("block_cap", 40), ("key_cap", 2), ("key_cap", 3), ("shrink_ratio", 0.1), ("shrink_ratio", 0.5), ("shrink_ratio", 1.0))


def _sensitivity(s, d: str) -> DataFrame:
    """Counted between classes of products of equal keys: neither a copy nor a true pair is laid out. Of a setting only its
    row is kept while the next is run."""
    held, groups = rib.settle(fx.part_classes(s, d), "classes"), rib.settle(fx.part_groups(s, d), "groups")
    rows = []
    for what, value in SETTINGS:
        measured = lambda cfg=fx.config("part", **{what: value}): metrics.group_quality(rib.class_edges(held, cfg), held, groups)
        rows.append(settle_alone(s, measured, "setting").select(F.lit(what).alias("parameter"), F.lit(float(value)).alias("value"), "pairs", "pc", "pq"))
    return _stacked(rows)


def _copied(s, d: str, copies: int) -> DataFrame:
    """The product index with every record ``copies`` times, under ids of its own: all blocks grow alike."""
    index = fx.part_index(s, d)
    step = index.agg((F.max("rid") + 1).alias("step"))
    each = index.crossJoin(F.broadcast(step)).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))  # one row
    return each.select((F.col("rid") + F.col("copy") * F.col("step")).alias("rid"), "keys")


def _ladder(s, d: str) -> DataFrame:
    """Records, postings and pairs of both methods over a table once, twice and four times; bench.py has the times."""
    rows = []
    for copies in (1, 2, 4):
        index = rib.settle(_copied(s, d, copies), "index")
        counted = index.agg(F.count("*").alias("records"), F.sum(F.size("keys")).cast("bigint").alias("postings"))
        for m, p in (("CapDrop", baselines.cap_drop(index, fx.CAPS["part"])), ("RIB", _rib(index, "part"))):
            pairs = p.agg(F.count("*").alias("pairs"))
            rows.append(counted.crossJoin(F.broadcast(pairs)).select(F.lit(copies).cast("bigint").alias("copies"), "records", "postings", F.lit(m).alias("method"), "pairs"))  # one row
    return _stacked(rows)


def _edges(weight: str):
    return lambda s, d: meta.weighted(fx.part_index(s, d), weight, purge=None).select("rid1", "rid2", F.round("w", 6).alias("w"))


def _pruned(how: str):
    return lambda s, d: meta.meta_blocking(fx.part_index(s, d), "cbs", how, purge=None)


def _cardinalities(s, d: str) -> DataFrame:
    rows = []
    for name in ("part", "customer", "docs"):
        made, held = _three(s, d, name)
        every = {"AllPairs": meta.edges(meta.block_postings(held, purge=None))} | made  # an edge is a pair that shares a key
        rows += [_counted(p).select(F.lit(name).alias("set"), F.lit(m).alias("method"), "pairs") for m, p in every.items()]
    return _stacked(rows)


def _reductions(s, d: str) -> DataFrame:
    many = _stacked([_INDEX[n](s, d).agg(F.count("*").alias("records")).withColumn("set", F.lit(n)) for n in ("part", "customer", "docs")])
    return _cardinalities(s, d).join(F.broadcast(many), "set").select("set", "method", metrics.reduction(F.col("pairs"), F.col("records")).alias("rr"))


def _total(name: str):
    return lambda s, d: baselines.all_pairs_cardinality(_INDEX[name](s, d)).select("keys", F.col("comparisons").cast("bigint").alias("comparisons"))


def _costs(s, d: str) -> DataFrame:
    """What comparing the orders' blocks exhaustively would cost."""
    sizes = rounds.key_stats(keys.postings(fx.orders_index(s, d))).filter("size > 1")
    return metrics.cost_model(sizes, MICROSECONDS, NODES, USD_PER_HOUR)


def _fitted(s, d: str) -> DataFrame:
    """Growth of the minutes that comparing the orders of a day takes with their number."""
    days = load(s, d, "orders").groupBy("o_orderdate").agg(F.count("*").alias("n")).filter("n > 1")
    minutes = F.expr("n * (n - 1) div 2").cast("double") * (MICROSECONDS / 60e6)
    return metrics.scaling(days.select((F.col("n") / 1e6).alias("millions"), minutes.alias("minutes")))


def _scored(s, d: str, pairs: DataFrame) -> DataFrame:
    words = {"w": text.words(F.col("text"))}
    return match.attach(pairs.select("rid1", "rid2"), fx.docs(s, d), "doc_id", words).withColumn("j", text.jaccard(F.col("w1"), F.col("w2")))


def _matched(s, d: str) -> DataFrame:
    """The method's candidates that are alike: alike pairs are joined first, among records that can have a candidate at all, and
    then asked for. Words are hashed once for both. Scores are judged rounded, so the join takes half a unit more."""
    docs, words = fx.docs(s, d), text.words(F.col("text"))
    hashed = hashes(docs, "doc_id", words)
    asked = Asked(hashed.select("rid", F.col("h").alias("keys")).filter("rid IS NOT NULL AND size(h) > 0"), fx.config("docs"))
    alike = jaccard_join(docs, "doc_id", words, 0.8 - 5e-7, hashed.join(asked.records(), "rid", "left_semi")).select("rid1", "rid2", F.round("jaccard", 6).alias("score"))
    alike = rib.settle(alike.filter("score >= 0.8"), "alike")
    return alike.join(asked.of(alike), ["rid1", "rid2"]).select("rid1", "rid2", "score")


def _clustered(s, d: str) -> DataFrame:
    return match.clusters(rib.settle(_matched(s, d), "matches"))


def _true(s, make: Callable[[], DataFrame]) -> DataFrame:
    """True pairs as a written table, of which alone files are left."""
    return settle_alone(s, lambda: make().select("rid1", "rid2"), "truth")


def _lsh_rows(s, df: DataFrame, rid: str, column, tokenizer, truth: DataFrame, off: list[keys.KeySpec]) -> DataFrame:
    """One row per setting of bands and width, and OFF where identity keys stand in for banded ones, against written true
    pairs. Banded keys, hashed to 64 bits, are in many blocks, whose pairs are counted; of a setting only counts are kept."""
    rows = [("OFF", settle_alone(s, lambda: metrics.quality(_rib(keys.build_index(df, rid, off), "lsh"), truth), "setting"))]

    def index(b: int, w: int) -> DataFrame:
        made = keys.build_index(df, rid, [keys.lsh(column, "text", b, w, tokenizer)])
        return rib.settle(made.select("rid", F.transform("keys", lambda k: F.xxhash64(k)).alias("keys")), "index")

    for b, w in ((1, 1), *minhash.LSH_GRID):
        found = _levels(lambda b=b, w=w: _blocks(index(b, w), fx.config("lsh", hash="h64")), truth)
        rows.append((f"{b},{w}", metrics.level_quality(found, 0)))
    return _stacked([row.select(F.lit(label).alias("setting"), "pairs", "pc", "pq") for label, row in rows])


def _page_truth(s, d: str) -> DataFrame:
    return jaccard_join(load(s, d, "pages"), "page_id", text.words(fx.page_text()), 0.8)


def _ablate_docs(s, d: str, truth: DataFrame | None = None) -> DataFrame:
    truth = _true(s, lambda: fx.docs_truth(s, d)) if truth is None else truth
    return _lsh_rows(s, fx.docs(s, d), "doc_id", "text", text.words, truth, [keys.identity("text")])


def _ablate_part(s, d: str) -> DataFrame:
    return _lsh_rows(s, fx.part(s, d), "p_partkey", "p_name", lambda c: text.qgrams(c, 3), _true(s, lambda: fx.part_truth(s, d)), [keys.identity("p_name")])


def _ablate_pages(s, d: str) -> DataFrame:
    return _lsh_rows(s, load(s, d, "pages"), "page_id", fx.page_text(), text.words, _true(s, lambda: _page_truth(s, d)), [keys.identity(fx.page_text(), "html")])


def _scatter(s, d: str) -> DataFrame:
    """The ablation's points and one of token keys kept in the smaller half of each record's blocks. Keys are hashed to 64 bits
    once the halves are taken; blocks that these leave with one record are none to the method either."""
    truth = _true(s, lambda: fx.docs_truth(s, d))

    def halved() -> DataFrame:
        few = meta.smallest(meta.block_postings(rib.settle(fx.docs_index(s, d), "index"), purge=None), 0.5)
        return few.groupBy("rid").agg(F.collect_list(F.xxhash64("key")).alias("keys"))

    token = _levels(lambda: _blocks(settle_alone(s, halved, "halved"), fx.config("docs", hash="h64")), truth)
    return _ablate_docs(s, d, truth).unionByName(metrics.level_quality(token, 0).select(F.lit("token 0.5").alias("setting"), "pairs", "pc", "pq"))


def _off(s, d: str) -> DataFrame:
    specs = [keys.identity("text"), keys.identity("source")]
    return metrics.quality(_rib(keys.build_index(fx.docs(s, d), "doc_id", specs), "lsh"), fx.docs_truth(s, d)).select("pairs", "pc", "pq")


def _token_vs_lsh(s, d: str) -> DataFrame:
    truth = rib.settle(fx.docs_truth(s, d).select("rid1", "rid2"), "truth")
    banded = keys.build_index(fx.docs(s, d), "doc_id", [keys.lsh("text", "text", 6, 7)])
    return _stacked([metrics.quality(_rib(i, n), truth).select(F.lit(label).alias("setting"), "pairs", "pc", "pq") for label, i, n in (("token", fx.docs_index(s, d), "docs"), ("lsh 6,7", banded, "lsh"))])


QUERIES = {
    "naive_customer": lambda s, d: baselines.all_pairs(fx.customer_index(s, d)),
    "meta_filter_part": lambda s, d: meta.block_postings(fx.part_index(s, d), purge=None, ratio=0.8).select("rid", printed(F.col("key")).alias("key")),
    "pc_part": lambda s, d: metrics.pc(_rib(fx.part_index(s, d), "part"), fx.part_truth(s, d)),
    "pq_part": lambda s, d: metrics.pq(_rib(fx.part_index(s, d), "part"), fx.part_truth(s, d)),
    "pq_oracle_docs": lambda s, d: metrics.pq_oracle(_scored(s, d, _rib(fx.docs_index(s, d), "docs")), F.col("j") >= 0.8),
    "partial_labels_docs": lambda s, d: metrics.quality(_rib(fx.docs_index(s, d), "docs"), _labelled_truth(s, d)),
    "card_table": _cardinalities,
    "rr_table": _reductions,
    "cost_model": _costs,
    "scaling_ladder_part": _ladder,
    "sensitivity_part": _sensitivity,
    "meta_broadcast_part": lambda s, d: meta.broadcast_edges(fx.part_index(s, d), purge=None),
    "scaling_fit": _fitted,
    "ablate_lsh_docs": _ablate_docs,
    "ablate_lsh_part": _ablate_part,
    "ablate_lsh_pages": _ablate_pages,
    "lsh_scatter_docs": _scatter,
    "lsh_off_docs": _off,
    "ablate_token_vs_lsh": _token_vs_lsh,
    "voter_standin_capdrop": lambda s, d: baselines.cap_drop(fx.voter_index(s, d), fx.CAPS["voter"]),
    "match_docs": _matched,
    "cluster_docs": _clustered,
    "dedup_docs": lambda s, d: match.survivors(fx.docs(s, d).select("doc_id"), "doc_id", _clustered(s, d)),
    "truth_docs": lambda s, d: fx.docs_truth(s, d).select("rid1", "rid2", F.round("jaccard", 6).alias("jaccard")),
    "rarity_orders": lambda s, d: match.rarity(load(s, d, "orders"), "o_orderpriority").select("value", F.round("weight", 6).alias("weight")),
}


def _labelled_truth(s, d: str) -> DataFrame:
    """Document truth restricted to pairs of labelled documents, as incomplete labels are."""
    some = load(s, d, "labels").select("doc_id").distinct()
    side = lambda n: some.select(F.col("doc_id").alias(f"rid{n}"))
    return fx.docs_truth(s, d).select("rid1", "rid2").join(side(1), "rid1", "left_semi").join(side(2), "rid2", "left_semi")


def _rib_sql(base: str, cap: int, depth: int, p: str = "") -> tuple[str, str]:
    return sql.rounds(base, cap, depth, p=p), f"SELECT rid1, rid2 FROM {p}pairs"


_BASE = {"part": (sql.PART, 2), "orders": (sql.ORDERS, 3), "customer": (sql.CUSTOMER, 2), "docs": (sql.DOCS, 4), "voter": (sql.VOTER, 3)}


def _three_sql(name: str, p: str = "") -> tuple[list[str], dict[str, str]]:
    base, depth = _BASE[name]
    cap = fx.CAPS[name]
    ctes = [sql.cap_drop(base, cap, p), sql.meta(base, "cbs", "wnp", p), sql.rounds(base, cap, depth, p=p)]
    return ctes, {"CapDrop": f"SELECT * FROM {p}capped", "MetaGraph": f"SELECT rid1, rid2 FROM {p}kept", "RIB": f"SELECT rid1, rid2 FROM {p}pairs"}


def _compared_sql(name: str, truth_cte: str, truth: str) -> str:
    ctes, made = _three_sql(name)
    return f"WITH {', '.join(ctes + ([truth_cte] if truth_cte else []))} " + " UNION ALL ".join(f"SELECT '{m}' AS method, pairs, pc, pq FROM ({sql.measured(p, truth)})" for m, p in made.items())


def _cards(shape: str) -> str:
    ctes, rows = [], []
    for name in ("part", "customer", "docs"):
        p = f"{name}_"
        more, made = _three_sql(name, p)
        ctes += [sql.all_pairs(_BASE[name][0], p), *more]
        made = {"AllPairs": f"SELECT * FROM {p}naive"} | made
        for m, q in made.items():
            n = f"(SELECT count(*) FROM ({q}))"
            of = f"(SELECT count(DISTINCT rid) FROM {p}ab)"
            rows.append(f"SELECT '{name}' AS \"set\", '{m}' AS method, " + (f"{n} AS pairs" if shape == "pairs" else f"round(1 - {n} / ({of} * ({of} - 1) / 2.0), 6) AS rr"))
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(rows)}"


def _at_point_sql(name: str, truth_cte: str, truth: str) -> str:
    base, depth = _BASE[name]
    caps = [int(fx.CAPS[name] * x) for x in POINTS]
    ctes = [sql.rounds(base, fx.CAPS[name], depth), "ours AS MATERIALIZED (SELECT rid1, rid2 FROM pairs)", *(sql.cap_drop(base, c, f"c{c}_") for c in caps)]
    ctes += ["tried AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT {i} AS nth, {c} AS cap, rid1, rid2 FROM c{c}_capped" for i, c in enumerate(caps)) + ")"]
    off = "abs(ln(greatest(1, count(*)) / CAST((SELECT count(*) FROM ours) AS DOUBLE)))"
    ctes += [f"best AS MATERIALIZED (SELECT cap FROM tried GROUP BY nth, cap ORDER BY {off}, nth LIMIT 1)", "there AS MATERIALIZED (SELECT rid1, rid2 FROM tried WHERE cap = (SELECT cap FROM best))"]
    rows = f"SELECT 'RIB' AS method, CAST({fx.CAPS[name]} AS BIGINT) AS cap, pairs, pc, pq FROM ({sql.measured('SELECT * FROM ours', truth)}) UNION ALL SELECT 'CapDrop', (SELECT CAST(cap AS BIGINT) FROM best), pairs, pc, pq FROM ({sql.measured('SELECT * FROM there', truth)})"
    return f"WITH {', '.join(ctes + ([truth_cte] if truth_cte else []))} {rows}"


def _sensitivity_sql() -> str:
    ctes, rows = [], []
    for i, (what, value) in enumerate(SETTINGS):
        at = {"block_cap": 20, "key_cap": 80, "shrink_ratio": 0.9} | {what: value}
        ctes.append(sql.rounds(sql.PART, at["block_cap"], 3, at["key_cap"], round(at["shrink_ratio"] * 1000), p=f"s{i}_"))
        rows.append(f"SELECT '{what}' AS parameter, CAST({value} AS DOUBLE) AS value, pairs, pc, pq FROM ({sql.measured(f'SELECT rid1, rid2 FROM s{i}_pairs', sql.PART_TRUTH)})")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(rows)}"


def _ladder_sql() -> str:
    ctes, rows = [f"once AS MATERIALIZED ({sql.PART})"], []
    for copies in (1, 2, 4):
        base = f"SELECT rid + c * (SELECT max(rid) + 1 FROM once) AS rid, key FROM once, range({copies}) AS r(c)"
        ctes += [f"l{copies} AS MATERIALIZED ({base})", sql.cap_drop(f"SELECT * FROM l{copies}", fx.CAPS["part"], f"l{copies}_"), sql.rounds(f"SELECT * FROM l{copies}", fx.CAPS["part"], 3, p=f"l{copies}_")]
        for m, made in (("CapDrop", "capped"), ("RIB", "pairs")):
            rows.append(f"SELECT CAST({copies} AS BIGINT) AS copies, (SELECT count(DISTINCT rid) FROM l{copies}) AS records, (SELECT count(*) FROM l{copies}) AS postings, '{m}' AS method, (SELECT count(*) FROM l{copies}_{made}) AS pairs")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(rows)}"


_DOCS_RIB = sql.rounds(sql.DOCS, 50, 4)
_PART_RIB = sql.rounds(sql.PART, 20, 2)
_MATCHED = f"{_DOCS_RIB}, {sql.truth_docs(0.8)}, matched AS MATERIALIZED (SELECT rid1, rid2, round(jaccard, 6) AS score FROM pairs JOIN tj USING (rid1, rid2) WHERE round(jaccard, 6) >= 0.8)"
_CLUSTERED = (
    f"WITH RECURSIVE {_MATCHED}, twoway AS MATERIALIZED (SELECT rid1 AS a, rid2 AS b FROM matched UNION SELECT rid2, rid1 FROM matched), "
    "walk AS (SELECT a AS rid, a AS seen FROM twoway UNION SELECT rid, b FROM walk JOIN twoway ON a = seen), clustered AS (SELECT rid, min(seen) AS cluster FROM walk GROUP BY rid)"
)


def _lsh_sql(tokens: str, truth_cte: str, truth: str, off: str, more: tuple[str, str, str] | None = None) -> str:
    settings = [("OFF", off)] + [(f"{b},{w}", f"SELECT rid, key FROM ({sql.lsh(tokens, 'text', b, w)})") for b, w in ((1, 1), *minhash.LSH_GRID)]
    ctes, rows = [truth_cte] if truth_cte else [], []
    for i, (label, base) in enumerate(settings):
        ctes.append(sql.rounds(base, fx.CAPS["lsh"], 3, p=f"s{i}_"))
        rows.append(f"SELECT '{label}' AS setting, pairs, pc, pq FROM ({sql.measured(f'SELECT rid1, rid2 FROM s{i}_pairs', truth)})")
    if more:
        ctes.append(more[0])
        rows.append(f"SELECT '{more[1]}' AS setting, pairs, pc, pq FROM ({sql.measured(more[2], truth)})")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(rows)}"


_PAGE_TOKENS = f"SELECT page_id AS rid, unnest({sql.words(sql.STRIPPED)}) AS t FROM pages"
_PAGE_TRUTH = (
    f"pw AS MATERIALIZED ({_PAGE_TOKENS}), pn AS (SELECT rid, count(*) AS n FROM pw GROUP BY rid), pc_ AS (SELECT a.rid AS rid1, b.rid AS rid2, count(*) AS c FROM pw a JOIN pw b ON a.t = b.t AND a.rid < b.rid GROUP BY 1, 2), "
    "ptruth AS MATERIALIZED (SELECT rid1, rid2 FROM pc_ JOIN pn x ON x.rid = rid1 JOIN pn y ON y.rid = rid2 WHERE CAST(c AS DOUBLE) / (x.n + y.n - c) >= 0.8)"
)
_PART_TOKENS = "SELECT DISTINCT p_partkey AS rid, substr(lower(p_name), i, 3) AS t FROM (SELECT p_partkey, p_name, unnest(range(1, length(p_name) - 1)) AS i FROM part)"
_OFF_DOCS = f"SELECT doc_id AS rid, {sql.identity('text', 'text')} AS key FROM documents"
_OFF_PAGES = f"SELECT page_id AS rid, {sql.identity('html', sql.STRIPPED)} AS key FROM pages"
_HALVED = (
    "SELECT rid, key FROM (SELECT *, row_number() OVER (PARTITION BY rid ORDER BY size, key) AS nth, count(*) OVER (PARTITION BY rid) AS every FROM "
    "(SELECT rid, key, count(*) OVER (PARTITION BY key) AS size FROM ({base})) WHERE size > 1) WHERE nth <= ceil(every * {ratio})"
)
_again = lambda base, ratio: f"SELECT rid, key FROM (SELECT rid, key, count(*) OVER (PARTITION BY key) AS n FROM ({_HALVED.format(base=base, ratio=ratio)})) WHERE n > 1"

ORACLE_SQL = {
    "naive_customer": f"WITH {sql.all_pairs(sql.CUSTOMER)} SELECT * FROM naive",
    "meta_filter_part": _again(sql.PART, 0.8),
    "pc_part": f"WITH {_PART_RIB} SELECT hits, total, pc AS value FROM ({sql.measured('SELECT rid1, rid2 FROM pairs', sql.PART_TRUTH)})",
    "pq_part": f"WITH {_PART_RIB} SELECT hits, pairs AS total, pq AS value FROM ({sql.measured('SELECT rid1, rid2 FROM pairs', sql.PART_TRUTH)})",
    "pq_oracle_docs": f"WITH {_DOCS_RIB}, {sql.truth_docs(0.8)} SELECT count(*) FILTER (WHERE jaccard >= 0.8) AS hits, count(*) AS total, round(CAST(count(*) FILTER (WHERE jaccard >= 0.8) AS DOUBLE) / count(*), 6) AS value FROM pairs LEFT JOIN tj USING (rid1, rid2)",
    "partial_labels_docs": f"WITH {_DOCS_RIB}, {sql.truth_docs(0.8)} {sql.measured('SELECT rid1, rid2 FROM pairs', 'SELECT * FROM truth WHERE rid1 IN (SELECT doc_id FROM labels) AND rid2 IN (SELECT doc_id FROM labels)')}",
    "card_table": _cards("pairs"),
    "rr_table": _cards("rr"),
    "cost_model": f"WITH z AS (SELECT max(n * (n - 1) // 2) AS most, sum(CAST(n * (n - 1) // 2 AS DECIMAL(38,0))) AS every FROM (SELECT count(*) AS n FROM ({sql.ORDERS}) GROUP BY key) WHERE n > 1) "
    f"SELECT 'heavy_value_days' AS name, round(CAST(most AS DOUBLE) * {MICROSECONDS} / 1e6 / 86400, 3) AS value FROM z UNION ALL SELECT 'naive_scoring_dollars', round(CAST(every AS DOUBLE) * {MICROSECONDS} / 1e6 / 3600 * {USD_PER_HOUR}, 3) FROM z "
    f"UNION ALL SELECT 'naive_scoring_worker_years', round(CAST(every AS DOUBLE) * {MICROSECONDS} / 1e6 / 86400 / 365.25, 3) FROM z UNION ALL SELECT 'naive_scoring_days', round(CAST(every AS DOUBLE) * {MICROSECONDS} / 1e6 / 86400 / {NODES}, 3) FROM z",
    "scaling_ladder_part": _ladder_sql(),
    "sensitivity_part": _sensitivity_sql(),
    "meta_broadcast_part": f"WITH {sql.meta(sql.PART, 'cbs', None)} SELECT rid1, rid2, w FROM edge",
    "scaling_fit": "SELECT round(regr_slope(minutes, millions), 6) AS slope, round(regr_intercept(minutes, millions), 6) AS intercept, round(regr_r2(minutes, millions), 6) AS r2, round(regr_slope(ln(minutes), ln(millions)), 6) AS loglog FROM "
    f"(SELECT n / 1e6 AS millions, CAST(n * (n - 1) // 2 AS DOUBLE) * {MICROSECONDS / 60e6!r} AS minutes FROM (SELECT count(*) AS n FROM orders GROUP BY o_orderdate HAVING count(*) > 1))",
    "ablate_lsh_docs": _lsh_sql(sql.DOC_TOKENS, sql.truth_docs(0.8), "SELECT * FROM truth", _OFF_DOCS),
    "ablate_lsh_part": _lsh_sql(_PART_TOKENS, "", sql.PART_TRUTH, f"SELECT p_partkey AS rid, {sql.identity('p_name', 'p_name')} AS key FROM part"),
    "ablate_lsh_pages": _lsh_sql(_PAGE_TOKENS, _PAGE_TRUTH, "SELECT * FROM ptruth", _OFF_PAGES),
    "lsh_scatter_docs": _lsh_sql(sql.DOC_TOKENS, sql.truth_docs(0.8), "SELECT * FROM truth", _OFF_DOCS, (sql.rounds(_again(sql.DOCS, 0.5), 50, 4, p="tok_"), "token 0.5", "SELECT rid1, rid2 FROM tok_pairs")),
    "lsh_off_docs": f"WITH {sql.truth_docs(0.8)}, {sql.rounds(_OFF_DOCS + ' UNION ALL SELECT doc_id, ' + sql.identity('source', 'source') + ' FROM documents', 20, 2)} SELECT pairs, pc, pq FROM ({sql.measured('SELECT rid1, rid2 FROM pairs', 'SELECT * FROM truth')})",
    "ablate_token_vs_lsh": f"WITH {sql.truth_docs(0.8)}, {sql.rounds(sql.DOCS, 50, 4, p='a_')}, {sql.rounds(sql.docs_lsh(6, 7), 20, 3, p='b_')} "
    f"SELECT 'token' AS setting, pairs, pc, pq FROM ({sql.measured('SELECT rid1, rid2 FROM a_pairs', 'SELECT * FROM truth')}) UNION ALL SELECT 'lsh 6,7', pairs, pc, pq FROM ({sql.measured('SELECT rid1, rid2 FROM b_pairs', 'SELECT * FROM truth')})",
    "voter_standin_capdrop": f"WITH {sql.cap_drop(sql.VOTER, 20)} SELECT * FROM capped",
    "match_docs": f"WITH {_MATCHED} SELECT rid1, rid2, score FROM matched",
    "cluster_docs": f"{_CLUSTERED} SELECT rid, cluster FROM clustered",
    "dedup_docs": f"{_CLUSTERED} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT rid FROM clustered WHERE rid <> cluster)",
    "truth_docs": f"WITH {sql.truth_docs(0.8)} SELECT rid1, rid2, round(jaccard, 6) AS jaccard FROM tj WHERE jaccard >= 0.8",
    "rarity_orders": "SELECT o_orderpriority AS value, round(ln((SELECT count(*) FROM orders) / CAST(count(*) AS DOUBLE)), 6) AS weight FROM orders GROUP BY 1",
}

for _name, (_base, _depth) in _BASE.items():
    if _name in ("part", "orders", "docs"):
        QUERIES[f"naive_card_{_name}"] = _total(_name)
        ORACLE_SQL[f"naive_card_{_name}"] = f"SELECT count(*) AS keys, CAST(sum(n * (n - 1) // 2) AS BIGINT) AS comparisons FROM (SELECT count(*) AS n FROM ({_base}) GROUP BY key HAVING count(*) > 1)"
        QUERIES[f"capdrop_{_name}"] = lambda s, d, n=_name: baselines.cap_drop(_INDEX[n](s, d), fx.CAPS[n])
        ORACLE_SQL[f"capdrop_{_name}"] = f"WITH {sql.cap_drop(_base, fx.CAPS[_name])} SELECT * FROM capped"
    if _name in _TRUTH:
        QUERIES[f"compare_methods_{_name}"] = _compared(_name)
        QUERIES[f"compare_at_point_{_name}"] = _at_point(_name)
ORACLE_SQL |= {
    "compare_methods_part": _compared_sql("part", "", sql.PART_TRUTH),
    "compare_methods_docs": _compared_sql("docs", sql.truth_docs(0.8), "SELECT * FROM truth"),
    "compare_methods_voter": _compared_sql("voter", "", sql.VOTER_TRUTH),
    "compare_at_point_part": _at_point_sql("part", "", sql.PART_TRUTH),
    "compare_at_point_docs": _at_point_sql("docs", sql.truth_docs(0.8), "SELECT * FROM truth"),
    "compare_at_point_voter": _at_point_sql("voter", "", sql.VOTER_TRUTH),
}
for _w in meta.WEIGHTS:
    QUERIES[f"meta_{_w}_part"] = _edges(_w)
    ORACLE_SQL[f"meta_{_w}_part"] = f"WITH {sql.meta(sql.PART, _w, None)} SELECT rid1, rid2, round(w, 6) AS w FROM edge"
for _how in meta.PRUNES:
    QUERIES[f"meta_{_how}_part"] = _pruned(_how)
    ORACLE_SQL[f"meta_{_how}_part"] = f"WITH {sql.meta(sql.PART, 'cbs', _how)} SELECT rid1, rid2 FROM kept"
