"""The main method and its steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import AS_PUBLISHED, BlockingConfig
from ..functions.hashing import md5_bits, printed
from ..operators import pairs as pair_ops
from ..operators import keys, rib, rounds, sketch
from . import fixtures as fx
from . import sql


def shown(df: DataFrame) -> DataFrame:
    return df.withColumn("key", printed(F.col("key")))


def _pairs(index, name: str, **changes):
    return lambda s, d: shown(rib.pairs_of(rib.run(index(s, d), fx.config(name, **changes)).blocks(), fx.config(name, **changes)))


def _first(s, d: str, index, name: str) -> tuple[DataFrame, BlockingConfig]:
    return rounds.seeded(index(s, d)), fx.config(name)


def _over(s, d: str, index, name: str, **changes) -> DataFrame:
    """(rid, key, size) of surviving top-level over-size keys."""
    long_df, cfg = _first(s, d, index, name)
    cfg = cfg.but(**changes)
    over = rounds.classify(rounds.key_stats(long_df), cfg)
    return rib.split(long_df, over, cfg, over.count())[1]


def _fit_blocks(s, d: str) -> DataFrame:
    long_df, cfg = _first(s, d, fx.orders_index, "orders")
    return shown(rounds.key_stats(long_df).filter(F.col("size").between(2, cfg.block_cap)).select("key", "size"))


def _twins(s, d: str) -> DataFrame:
    long_df, cfg = _first(s, d, fx.docs_index, "docs")
    over = rounds.key_stats(long_df).filter("size > 5")
    kept = rounds.drop_twins(over).select("fp", "size", F.col("key").alias("survivor"))
    return over.join(kept, ["fp", "size"]).select(printed(F.col("key")).alias("key"), printed(F.col("survivor")).alias("survivor"))


def _classes(s, d: str) -> DataFrame:
    """Postings of top-level document keys by class, all keys taken as maybe over-size."""
    long_df, cfg = _first(s, d, fx.docs_index, "docs")
    kinds = rounds.classify(rounds.key_stats(long_df), cfg.but(block_cap=5))
    return long_df.join(kinds, "key", "left").groupBy(F.coalesce("kind", F.lit("fit")).alias("class")).agg(F.count("*").alias("n"))


def _cut(s, d: str) -> DataFrame:
    held = _over(s, d, fx.docs_index, "docs", block_cap=5).groupBy(F.col("rid").alias("doc_id")).agg(F.count("*").alias("n_over"))
    return held.filter("n_over > 80")


def _shrink(s, d: str) -> DataFrame:
    cfg = fx.config("docs")
    child = rounds.intersect(_over(s, d, fx.docs_index, "docs"), cfg)
    over = rounds.key_stats(child).filter(F.col("size") > cfg.block_cap)
    return over.select(printed(F.col("key")).alias("key"), "size", "psize", rounds.shrinks(F.col("size"), F.col("psize"), cfg).alias("pass"))


def _report(s, d: str) -> DataFrame:
    out = None
    for name, index in (("orders", fx.orders_index), ("part", fx.part_index), ("customer", fx.customer_index)):
        rows = rib.run(index(s, d), fx.config(name)).report_frame().select(F.lit(name).alias("set"), F.col("round").cast("bigint").alias("round"), "fit", "over", "pass_ratio", "survivors")
        out = rows if out is None else out.unionByName(rows)
    return out


def _diagnosed(s, d: str) -> DataFrame:
    """Copies and stalled keys of each round, counted exactly and by a sketch, which must agree."""
    out = None
    for counting in ("exact", "sketch"):
        for name, index in (("orders", fx.orders_index), ("part", fx.part_index), ("customer", fx.customer_index)):
            told = rib.run(index(s, d), fx.config(name, counting=counting)).diagnostics_frame()
            rows = told.select(F.lit(name).alias("set"), "counting", F.col("round").cast("bigint").alias("round"), "twins", "stalled").filter("twins + stalled > 0")
            out = rows if out is None else out.unionByName(rows)
    return out


def _blocks(s, d: str) -> DataFrame:
    made = rib.run(fx.part_index(s, d), fx.config("part")).blocks()
    return made.select(printed(F.col("key")).alias("key"), "size", F.array_join(F.col("rids").cast("array<string>"), ",").alias("rids"))


def _every(s, d: str) -> DataFrame:
    return shown(pair_ops.expand(rib.run(fx.part_index(s, d), fx.config("part")).blocks()).select("rid1", "rid2", "key"))


def _packed(s, d: str) -> DataFrame:
    return pair_ops.pack(rib.pairs_of(rib.run(fx.part_index(s, d), fx.config("part")).blocks(), fx.config("part")))


def _bits(s, d: str) -> DataFrame:
    """Set bits after a round trip through the bitmap, full blocks included."""
    packed = _packed(s, d).withColumn("bitmap", pair_ops.encode("bits", "n"))
    return packed.select(printed(F.col("key")).alias("key"), F.explode(pair_ops.decode("bitmap", "n")).alias("bit"))


def _grid(s, d: str) -> DataFrame:
    """Places of all pairs in the bitmaps of orders as blocks of their lines, with the number of orders per size."""
    from ..sources.tables import load

    sizes = load(s, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).filter(F.col("n").between(2, fx.CAPS["orders"]))
    n = sizes.groupBy("n").agg(F.count("*").alias("blocks"))
    ij = n.select("n", "blocks", F.explode(F.expr("sequence(0L, n - 2)")).alias("i")).select("n", "blocks", "i", F.explode(F.expr("sequence(i + 1, n - 1)")).alias("j"))
    return ij.select("n", "blocks", "i", "j", pair_ops.bit_index(F.col("i"), F.col("j"), F.col("n")).alias("bit"))


def _never_under(s, d: str) -> DataFrame:
    long_df, _ = _first(s, d, fx.docs_index, "docs")
    estimate = sketch.estimator(s, sketch.build(long_df, 0.001, 0.99))
    return rounds.key_stats(long_df).agg(F.count_if(estimate(F.col("key")) < F.col("size")).alias("violations"))


def _bucket(d, key):
    return F.pmod(md5_bits(F.concat(d.cast("string"), F.lit(":"), printed(key))), F.lit(4096))


def _rough(s, d: str) -> DataFrame:
    """Keys that a narrow sketch calls fit, and how many of them are not: none may be."""
    long_df, cfg = _first(s, d, fx.docs_index, "docs")
    fit, maybe = rib.rough_split(long_df, cfg.but(counting="sketch", sketch_eps=0.0005))
    sizes = rounds.key_stats(long_df).select("key", "size")
    judged = fit.select("key", F.lit("fit").alias("class")).unionByName(maybe.select("key", F.lit("maybe").alias("class"))).distinct().join(sizes, "key")
    return judged.groupBy("class").agg(F.count("*").alias("keys"), F.count_if(F.col("size") > cfg.block_cap).alias("over"))


def _lost(s, d: str) -> DataFrame:
    """Fit keys of the second generation that a crude sketch loses, by what the shrink test looks at."""
    cfg = fx.config("docs").but(counting="sketch", sketch_eps=0.002, sketch_confidence=0.5)
    child = rounds.intersect(_over(s, d, fx.docs_index, "docs"), cfg)
    fit = rounds.key_stats(child).filter(F.col("size").between(2, cfg.block_cap)).select("key")
    out = None
    for mode in ("estimate", "exact"):
        settled, maybe = rib.rough_split(child, cfg.but(shrink_on=mode))
        kept = settled.select("key").union(maybe.select("key")).distinct()
        row = fit.join(kept, "key", "left_anti").agg(F.count("*").alias("lost")).select(F.lit(mode).alias("mode"), "lost")
        out = row if out is None else out.unionByName(row)
    return out


def _linked(s, d: str) -> DataFrame:
    cfg = fx.config("link")
    got = rib.pairs_of(rib.run(fx.link_index(s, d), cfg).blocks(), cfg, fx.across)
    odd = F.when(F.col("rid1") % 2 == 1, F.col("rid1")).otherwise(F.col("rid2"))
    even = F.when(F.col("rid1") % 2 == 1, F.col("rid2")).otherwise(F.col("rid1"))
    return got.select((even / 2).cast("bigint").alias("doc_id"), ((odd - 1) / 2).cast("bigint").alias("item_id"))


def _heavy(s, d: str) -> DataFrame:
    """Per attribute: over-size keys at the cap, and the share of records that have one."""
    from ..sources.tables import load

    out = None
    for attribute, spec in zip(("o_custkey", "o_orderstatus", "o_orderdate", "o_orderpriority", "o_totalprice"), fx.orders_specs(), strict=True):
        sizes = keys.postings(keys.build_index(load(s, d, "orders"), "o_orderkey", [spec])).groupBy("key").agg(F.count("*").alias("n"))
        over = F.col("n") > fx.CAPS["orders"]
        row = sizes.agg(F.count_if(over).alias("over_keys"), F.round(F.sum(F.when(over, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("over_share")).withColumn("attr", F.lit(attribute))
        out = row if out is None else out.unionByName(row)
    return out.select("attr", "over_keys", "over_share")


def _stalls(s, d: str) -> DataFrame:
    """Classes of keys in the first two rounds where attributes repeat."""
    cfg = fx.config("lineitem")
    long_df = rounds.seeded(fx.lineitem_index(s, d, 4, 2))
    out = None
    for t in range(2):
        stats = rounds.key_stats(long_df)
        over = rib.settle(rounds.classify(stats, cfg), "over")
        fit = stats.filter(F.col("size").between(2, cfg.block_cap)).select(F.lit("fit").alias("class"))
        row = over.select(F.col("kind").alias("class")).unionByName(fit).groupBy("class").agg(F.count("*").alias("n")).withColumn("round", F.lit(t).cast("bigint"))
        out = row if out is None else out.unionByName(row)
        long_df = rib.settle(rounds.intersect(rib.split(long_df, over, cfg, 0)[1], cfg), "next")
    return out.select("round", "class", "n")


QUERIES = {
    "rib_part": _pairs(fx.part_index, "part", pair_dedup="shuffle"),
    "rib_part_propagate": _pairs(fx.part_index, "part", pair_dedup="propagate"),
    "rib_part_sketch": _pairs(fx.part_index, "part", counting="sketch"),
    "rib_part_bucket": _pairs(fx.part_index, "part", counting="sketch", sketch_bytes=1),
    "rib_part_survivor_sketch": _pairs(fx.part_index, "part", survivor_store="sketch"),
    "rib_part_published": lambda s, d: shown(rib.pairs_of(rib.run(fx.part_index(s, d), AS_PUBLISHED.but(block_cap=20, sketch_eps=1e-5)).blocks(), AS_PUBLISHED)),
    "rib_orders": _pairs(fx.orders_index, "orders"),
    "rib_customer": _pairs(fx.customer_index, "customer"),
    "rib_pivot_customer": _pairs(fx.customer_index, "customer", counting="pivot"),
    "rib_shuffle_join_customer": _pairs(fx.customer_index, "customer", survivor_store="join"),
    "rib_lineitem": lambda s, d: _pairs(fx.lineitem_index, "lineitem")(s, d).select("rid1", "rid2"),
    "rib_token_docs": _pairs(fx.docs_index, "docs"),
    "rib_token_pages": _pairs(fx.pages_index, "pages"),
    "voter_standin_rib": _pairs(fx.voter_index, "voter"),
    "rib_round0_blocks": _fit_blocks,
    "key_stats_orders": lambda s, d: shown(rounds.key_stats(_first(s, d, fx.orders_index, "orders")[0], id_hash=md5_bits).select("key", "size", "fp")),
    "over_keys_orders": lambda s, d: shown(rounds.key_stats(_first(s, d, fx.orders_index, "orders")[0]).filter("size > 50").select("key", "size")),
    "twins_docs": _twins,
    "settle_docs": _classes,
    "intersect_orders": lambda s, d: shown(rounds.intersect(_over(s, d, fx.orders_index, "orders"), fx.config("orders"))),
    "keycap_docs": _cut,
    "shrink_docs": _shrink,
    "rib_rounds_report": _report,
    "rib_rounds_diagnostics": _diagnosed,
    "rib_blocks_part": _blocks,
    "pairs_expand_part": _every,
    "pack_part": lambda s, d: shown(_packed(s, d).select("key", "n", "edges", "is_full")),
    "bitmap_bits": _bits,
    "bit_index_grid": _grid,
    "cms_never_under": _never_under,
    "cms_table_docs": lambda s, d: sketch.bucket_table(_first(s, d, fx.docs_index, "docs")[0], 4, 4096, bucket=_bucket).select(F.col("d").cast("bigint").alias("d"), "bucket", "n"),
    "rough_split_docs": _rough,
    "shrink_exact_vs_est": _lost,
    "link_docs_benchmark": _linked,
    "heavy_value_orders": _heavy,
    "twins_stall_lineitem": _stalls,
}


def _all(base: str, cap: int, depth: int, columns: str = "rid1, rid2, key, size") -> str:
    return f"WITH {sql.rounds(base, cap, depth)} SELECT {columns} FROM pairs"


def _reported(name: str, base: str, cap: int, depth: int) -> tuple[str, str]:
    p = f"{name}_"
    rows = " UNION ALL ".join(
        f"SELECT '{name}' AS \"set\", CAST({t} AS BIGINT) AS round, (SELECT count(*) FROM {p}st{t} WHERE size BETWEEN 2 AND {cap}) AS fit, (SELECT count(*) FROM {p}st{t} WHERE size > {cap}) AS over, "
        f"(SELECT count(*) FROM {p}ov{t}) AS pass_ratio, (SELECT count(*) FROM {p}sv{t}) AS survivors"
        for t in range(depth)
    )
    return sql.rounds(base, cap, depth, p=p), rows


_reports = [_reported("orders", sql.ORDERS, 50, 3), _reported("part", sql.PART, 20, 2), _reported("customer", sql.CUSTOMER, 20, 2)]
_heavy_sql = " UNION ALL ".join(
    f"SELECT '{a}' AS attr, count(*) FILTER (WHERE n > 50) AS over_keys, round(CAST(coalesce(sum(n) FILTER (WHERE n > 50), 0) AS DOUBLE) / sum(n), 6) AS over_share FROM (SELECT {v} AS v, count(*) AS n FROM orders GROUP BY 1)"
    for a, v in (("o_custkey", "o_custkey"), ("o_orderstatus", "o_orderstatus"), ("o_orderdate", "o_orderdate"), ("o_orderpriority", "o_orderpriority"), ("o_totalprice", "floor(o_totalprice / 10000)"))
)
_packed_sql = f"WITH {sql.rounds(sql.PART, 20, 2)}, m AS (SELECT key, rid1 AS rid FROM pairs UNION SELECT key, rid2 FROM pairs), sz AS (SELECT key, count(*) AS n FROM m GROUP BY key)"
_stall_rows = " UNION ALL ".join(
    f"SELECT CAST({t} AS BIGINT) AS round, class, n FROM (SELECT 'fit' AS class, count(*) AS n FROM st{t} WHERE size BETWEEN 2 AND 50 UNION ALL SELECT 'stalled', (SELECT count(*) FROM st{t} WHERE size > 50) - (SELECT count(*) FROM ov{t}) "
    f"UNION ALL SELECT 'twin', (SELECT count(*) FROM ov{t}) - (SELECT count(*) FROM sv{t}) UNION ALL SELECT 'over', count(*) FROM sv{t}) WHERE n > 0"
    for t in range(2)
)

ORACLE_SQL = {
    "rib_part": _all(sql.PART, 20, 2),
    "rib_orders": _all(sql.ORDERS, 50, 3),
    "rib_customer": _all(sql.CUSTOMER, 20, 2),
    "rib_lineitem": _all(sql.lineitem(), 50, 4, "rid1, rid2"),
    "rib_token_docs": _all(sql.DOCS, 50, 4),
    "rib_token_pages": _all(sql.PAGES, 20, 3),
    "voter_standin_rib": _all(sql.VOTER, 20, 3),
    "rib_round0_blocks": f"SELECT key, count(*) AS size FROM ({sql.ORDERS}) GROUP BY key HAVING count(*) BETWEEN 2 AND 50",
    "key_stats_orders": f"SELECT key, count(*) AS size, bit_xor(CAST('0x' || substr(md5(CAST(rid AS VARCHAR)), 1, 15) AS BIGINT)) AS fp FROM ({sql.ORDERS}) GROUP BY key",
    "over_keys_orders": f"SELECT key, count(*) AS size FROM ({sql.ORDERS}) GROUP BY key HAVING count(*) > 50",
    "twins_docs": f"WITH g AS (SELECT key, md5(string_agg(CAST(rid AS VARCHAR), ',' ORDER BY rid)) AS ids FROM ({sql.DOCS}) GROUP BY key HAVING count(*) > 5) SELECT key, min(key) OVER (PARTITION BY ids) AS survivor FROM g",
    "settle_docs": f"WITH {sql.rounds(sql.DOCS, 5, 1)} SELECT class, count(*) AS n FROM (SELECT CASE WHEN st0.size <= 5 THEN 'fit' WHEN sv0.key IS NULL THEN 'twin' ELSE 'over' END AS class FROM k0 JOIN st0 USING (key) LEFT JOIN sv0 USING (key)) GROUP BY class",
    "intersect_orders": f"WITH {sql.rounds(sql.ORDERS, 50, 1)} SELECT rid, key, psize FROM k1",
    "keycap_docs": f"WITH {sql.rounds(sql.DOCS, 5, 1)} SELECT rid AS doc_id, count(*) AS n_over FROM in0 GROUP BY rid HAVING count(*) > 80",
    "shrink_docs": f"WITH {sql.rounds(sql.DOCS, 50, 2)} SELECT key, size, psize, size * 1000 <= psize * 900 AS pass FROM st1 WHERE size > 50",
    "rib_rounds_report": f"WITH {', '.join(c for c, _ in _reports)} SELECT * FROM ({' UNION ALL '.join(r for _, r in _reports)}) WHERE fit + over > 0",
    "rib_rounds_diagnostics": f"WITH {', '.join(c for c, _ in _reports)} SELECT \"set\", counting, round, pass_ratio - survivors AS twins, over - pass_ratio AS stalled FROM ({' UNION ALL '.join(r for _, r in _reports)}), (VALUES ('exact'), ('sketch')) AS c(counting) WHERE over > survivors",
    "rib_blocks_part": f"WITH {sql.rounds(sql.PART, 20, 2)} SELECT key, count(*) AS size, string_agg(CAST(rid AS VARCHAR), ',' ORDER BY rid) AS rids FROM fit GROUP BY key",
    "pairs_expand_part": f"WITH {sql.rounds(sql.PART, 20, 2)} SELECT rid1, rid2, key FROM every",
    "pack_part": f"{_packed_sql} SELECT key, any_value(n) AS n, count(*) AS edges, count(*) = any_value(n) * (any_value(n) - 1) // 2 AS is_full FROM pairs JOIN sz USING (key) GROUP BY key",
    "bitmap_bits": f"{_packed_sql}, pos AS (SELECT key, rid, row_number() OVER (PARTITION BY key ORDER BY rid) - 1 AS at FROM m) SELECT p.key, CAST(a.at * n - a.at * (a.at + 1) // 2 + b.at - a.at - 1 AS BIGINT) AS bit FROM pairs p JOIN sz USING (key) JOIN pos a ON a.key = p.key AND a.rid = rid1 JOIN pos b ON b.key = p.key AND b.rid = rid2",
    "bit_index_grid": "SELECT n, blocks, i, j, row_number() OVER (PARTITION BY n ORDER BY i, j) - 1 AS bit FROM (SELECT n, count(*) AS blocks FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey) "
    f"WHERE n BETWEEN 2 AND {fx.CAPS['orders']} GROUP BY n), range(0, {fx.CAPS['orders']}) AS b(i), range(0, {fx.CAPS['orders']}) AS c(j) WHERE i < j AND j < n",
    "cms_never_under": "SELECT CAST(0 AS BIGINT) AS violations",
    "cms_table_docs": f"SELECT CAST(d AS BIGINT) AS d, CAST('0x' || substr(md5(CAST(d AS VARCHAR) || ':' || key), 1, 15) AS BIGINT) % 4096 AS bucket, count(*) AS n FROM ({sql.DOCS}), range(0, 4) AS r(d) GROUP BY 1, 2",
    "link_docs_benchmark": f"WITH {sql.rounds(sql.LINK, 20, 4)} SELECT DISTINCT CAST(CASE WHEN rid1 % 2 = 1 THEN rid2 ELSE rid1 END // 2 AS BIGINT) AS doc_id, CAST((CASE WHEN rid1 % 2 = 1 THEN rid1 ELSE rid2 END - 1) // 2 AS BIGINT) AS item_id FROM pairs WHERE rid1 % 2 <> rid2 % 2",
    "heavy_value_orders": _heavy_sql,
    "twins_stall_lineitem": f"WITH {sql.rounds(sql.lineitem(4, 2), 50, 2)} {_stall_rows}",
}
for _same, _of in (("rib_part_propagate", "rib_part"), ("rib_part_sketch", "rib_part"), ("rib_part_bucket", "rib_part"), ("rib_part_published", "rib_part"), ("rib_pivot_customer", "rib_customer"), ("rib_shuffle_join_customer", "rib_customer")):
    ORACLE_SQL[_same] = ORACLE_SQL[_of]
