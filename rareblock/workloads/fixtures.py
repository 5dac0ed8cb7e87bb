"""Records, key settings and truths of the workloads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import BlockingConfig
from ..functions import text
from ..operators import keys
from ..operators.simjoin import jaccard_join
from ..sources.tables import LINEITEM_KEY, load, numbered_rid

#: Caps small enough that over-size blocks exist on tables of this size.
CAPS = {"part": 20, "orders": 50, "customer": 20, "voter": 20, "docs": 50, "pages": 20, "lineitem": 50, "lsh": 20, "link": 20}
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


def config(name: str, **changes) -> BlockingConfig:
    return BlockingConfig(block_cap=CAPS[name], counting="exact").but(**changes)


def part(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part")


def part_specs() -> list[keys.KeySpec]:
    cents = F.round(F.col("p_retailprice") * 100).cast("bigint")
    return [keys.identity("p_name"), keys.identity("p_brand"), keys.identity("p_type"), keys.identity("p_size"), keys.identity(cents, "p_retailprice")]


def part_index(spark: SparkSession, d: str) -> DataFrame:
    return keys.build_index(part(spark, d), "p_partkey", part_specs())


PRODUCT = ("p_name", "p_brand", "p_type")


def part_classes(spark: SparkSession, d: str) -> DataFrame:
    """(rid, keys, n, g): products of equal keys and of one group of part_truth(), g, counted. No id is sent but the least."""
    g = F.when(F.concat(*PRODUCT).isNotNull(), F.struct(*PRODUCT)).alias("g")
    index = keys.build_index(part(spark, d), "p_partkey", part_specs(), keep=(g,))
    return index.groupBy(F.array_sort("keys").alias("keys"), "g").agg(F.min("rid").alias("rid"), F.count("*").alias("n")).select("rid", "keys", "n", "g")


def part_groups(spark: SparkSession, d: str) -> DataFrame:
    """(n): how many records each group of part_truth() has."""
    return part(spark, d).na.drop(subset=list(PRODUCT)).groupBy(*PRODUCT).agg(F.count("*").alias("n"))


def orders_specs() -> list[keys.KeySpec]:
    return [
        keys.identity("o_custkey"), keys.identity("o_orderstatus"), keys.identity(F.date_format("o_orderdate", "yyyy-MM-dd"), "o_orderdate"),
        keys.identity("o_orderpriority"), keys.identity(F.floor(F.col("o_totalprice") / 10000).cast("bigint"), "o_totalprice"),
    ]


def orders_index(spark: SparkSession, d: str) -> DataFrame:
    return keys.build_index(load(spark, d, "orders"), "o_orderkey", orders_specs())


def customer_index(spark: SparkSession, d: str) -> DataFrame:
    specs = [keys.identity("c_nationkey"), keys.identity("c_mktsegment"), keys.identity(F.floor(F.col("c_acctbal") / 500).cast("bigint"), "bal_bin")]
    return keys.build_index(load(spark, d, "customer"), "c_custkey", specs)


def voter(spark: SparkSession, d: str) -> DataFrame:
    """Two snapshots of customers, the second edited by arithmetic on the key; rid = 2 * key + snapshot."""
    c, k = load(spark, d, "customer"), F.col("c_custkey")
    old = c.select((k * 2).alias("rid"), "c_name", "c_nationkey", "c_mktsegment", F.floor(F.col("c_acctbal") / 500).cast("bigint").alias("bal_bin"), "c_custkey")
    place = F.array_position(F.array(*map(F.lit, SEGMENTS)), F.col("c_mktsegment"))
    after = F.element_at(F.array(*map(F.lit, SEGMENTS)), (place % len(SEGMENTS) + 1).cast("int"))
    edit = lambda n, changed, c: F.when(k % n == 0, changed).otherwise(c)
    new = c.select(
        (k * 2 + 1).alias("rid"), edit(7, F.replace("c_name", F.lit("Customer"), F.lit("Customr")), F.col("c_name")).alias("c_name"),
        edit(5, (F.col("c_nationkey") + 1) % 25, F.col("c_nationkey")).cast("int").alias("c_nationkey"), edit(11, after, F.col("c_mktsegment")).alias("c_mktsegment"),
        F.floor((F.col("c_acctbal") + F.when(k % 3 == 0, 1000).otherwise(0)) / 500).cast("bigint").alias("bal_bin"), "c_custkey",
    )
    return old.unionByName(new)


def voter_index(spark: SparkSession, d: str) -> DataFrame:
    return keys.build_index(voter(spark, d), "rid", [keys.identity(c) for c in ("c_name", "c_nationkey", "c_mktsegment", "bal_bin")])


def voter_truth(spark: SparkSession, d: str) -> DataFrame:
    k = F.col("c_custkey")
    return load(spark, d, "customer").select((k * 2).alias("rid1"), (k * 2 + 1).alias("rid2"))


def docs(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents")


def docs_index(spark: SparkSession, d: str) -> DataFrame:
    return keys.build_index(docs(spark, d), "doc_id", [keys.token(["text"])])


def page_text() -> Column:
    return text.strip_html(F.col("html"))


def pages_index(spark: SparkSession, d: str) -> DataFrame:
    return keys.build_index(load(spark, d, "pages"), "page_id", [keys.token([page_text()])])


def docs_lsh_index(spark: SparkSession, d: str, bands: int, width: int) -> DataFrame:
    return keys.build_index(docs(spark, d), "doc_id", [keys.lsh("text", "text", bands, width)])


def docs_truth(spark: SparkSession, d: str, least: float = 0.8) -> DataFrame:
    return jaccard_join(docs(spark, d), "doc_id", text.words(F.col("text")), least)


def part_truth(spark: SparkSession, d: str) -> DataFrame:
    side = lambda n: part(spark, d).select(F.col("p_partkey").alias(f"rid{n}"), "p_name", "p_brand", "p_type")
    return side(1).join(side(2), ["p_name", "p_brand", "p_type"]).filter("rid1 < rid2").select("rid1", "rid2")


def lineitem(spark: SparkSession, d: str) -> DataFrame:
    return numbered_rid(load(spark, d, "lineitem"), *LINEITEM_KEY)


_LINE = ("l_partkey", "l_suppkey", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus")


def line_value(c: str) -> Column:
    """Doubles as whole hundredths, so that any engine prints them alike."""
    return F.round(F.col(c) * 100).cast("bigint") if c in ("l_quantity", "l_discount", "l_tax") else F.col(c)


def lineitem_index(spark: SparkSession, d: str, copies: int = 1, statuses: int = 1) -> DataFrame:
    """Eight identity keys; copies and statuses repeat ship date and line status as attributes of their own."""
    specs = [keys.identity(line_value(c), c) for c in _LINE]
    specs += [keys.identity(F.date_format("l_shipdate", "yyyy-MM-dd"), f"l_shipdate{i or ''}") for i in range(copies)]
    specs += [keys.identity("l_linestatus", f"l_linestatus{i}") for i in range(1, statuses)]
    return keys.build_index(lineitem(spark, d), "rid", specs)


def link_index(spark: SparkSession, d: str) -> DataFrame:
    """Documents and benchmark items in one id space: rid = 2 * id, or 2 * id + 1 for items."""
    both = docs(spark, d).select((F.col("doc_id") * 2).alias("rid"), "text").unionByName(load(spark, d, "benchmark").select((F.col("item_id") * 2 + 1).alias("rid"), "text"))
    return keys.build_index(both, "rid", [keys.token(["text"])])


def across(a: Column, b: Column) -> Column:
    """One id of each side."""
    return a % 2 != b % 2
