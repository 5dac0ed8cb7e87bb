"""The method's functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .minhash import PRIME


class BlockPairs:
    """LATERAL block_pairs(rids): the pairs of a block and their bitmap places."""

    def eval(self, rids) -> Iterator[tuple[int, int, int]]:
        ids, bit = sorted(rids), 0
        for i, a in enumerate(ids):
            for b in ids[i + 1 :]:
                yield a, b, bit
                bit += 1


class KeyGrid:
    """key_grid(b, w): the place of every minimum in its band."""

    def eval(self, b: int, w: int) -> Iterator[tuple[int, int]]:
        for i in range(b * w):
            yield i // w, i % w


_part = lambda letter: f"CAST(conv(substr(md5(concat('{letter}', i)), 1, 7), 16, 10) AS BIGINT)"
_minima = (
    "transform(sequence(0, m - 1), i -> array_min(transform(tokens, t -> "
    f"(({_part('a')} | 1) * CAST(conv(substr(md5(t), 1, 7), 16, 10) AS BIGINT) + {_part('b')}) % {PRIME}L)))"
)
# SQL functions by name, with arguments, type and body; Catalyst inlines them.
FUNCTIONS = {
    "rb_tokens": ("s STRING", "ARRAY<STRING>", r"array_distinct(regexp_extract_all(lower(s), '[\\p{L}\\p{N}]+', 0))"),
    "rb_qgrams": ("s STRING, q INT", "ARRAY<STRING>", "CASE WHEN length(s) >= q THEN array_distinct(transform(sequence(1, length(s) - q + 1), i -> substring(lower(s), i, q))) ELSE array() END"),
    "rb_identity_key": ("attr STRING, v STRING", "BINARY", r"unhex(md5(concat(attr, '\u001f', lower(trim(v)))))"),
    "rb_jaccard": ("a ARRAY<STRING>, b ARRAY<STRING>", "DOUBLE", "size(array_intersect(a, b)) / nullif(size(array_union(a, b)), 0)"),
    "rb_bit_index": ("i BIGINT, j BIGINT, n BIGINT", "BIGINT", "i * n - shiftright(i * (i + 1), 1) + j - i - 1"),
    "rb_minhash": ("tokens ARRAY<STRING>, m INT", "ARRAY<BIGINT>", f"CASE WHEN size(tokens) > 0 THEN {_minima} END"),
    "rb_lsh_keys": (
        "sig ARRAY<BIGINT>, b INT, w INT, attr STRING", "ARRAY<BINARY>",
        r"transform(sequence(0, b - 1), i -> unhex(md5(concat(attr, '\u001f', i, '\u001f', array_join(transform(slice(sig, i * w + 1, w), x -> CAST(x AS STRING)), '-')))))",
    ),
    "rb_lsh_prob": ("b INT, w INT, j DOUBLE", "DOUBLE", "1 - power(1 - power(j, w), b)"),
}


def register(spark: SparkSession) -> None:
    for name, (arguments, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("block_pairs", udtf(BlockPairs, returnType="rid1: bigint, rid2: bigint, bit: bigint"))
    spark.udtf.register("key_grid", udtf(KeyGrid, returnType="band: int, place: int"))
