"""MinHash signatures and banded keys.

Tokens are hashed once to 28 bits; hash i of a token x is (a_i * x + c_i) mod 2**31 - 1, whose product stays
below 2**56. Coefficients come from md5 of labels, so any engine can compute them again.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hashing import SEPARATOR

PRIME = 2**31 - 1
#: The published settings (bands, hashes per band), from strict to liberal.
LSH_GRID = ((3, 8), (6, 7), (10, 6), (12, 5), (14, 4), (16, 3))


def coefficients(m: int, seed: str = "") -> list[tuple[int, int]]:
    part = lambda label: int(hashlib.md5(label.encode()).hexdigest()[:7], 16)
    return [(part(f"a{seed}{i}") | 1, part(f"b{seed}{i}")) for i in range(m)]


def token_hashes(tokens: Column) -> Column:
    return F.transform(tokens, lambda t: F.conv(F.substring(F.md5(t.cast("binary")), 1, 7), 16, 10).cast("bigint"))


def signature(tokens: Column, m: int, seed: str = "") -> Column:
    """m minima, null if there is no token. All minima come from one transform over the coefficients, so the
    token hashes are bound once."""
    pairs = F.array(*[F.struct(F.lit(a).cast("bigint").alias("a"), F.lit(c).cast("bigint").alias("c")) for a, c in coefficients(m, seed)])
    bound = F.transform(F.array(token_hashes(tokens)), lambda h: F.transform(pairs, lambda p: F.array_min(F.transform(h, lambda x: (p["a"] * x + p["c"]) % PRIME))))
    return F.when(F.size(tokens) > 0, F.element_at(bound, 1))


def signature_udf(m: int, seed: str = ""):
    """The same minima from an array of 28-bit token hashes, by numpy over Arrow batches."""
    a, c = (np.array(x, "i8") for x in zip(*coefficients(m, seed), strict=True))

    @F.pandas_udf("array<bigint>")
    def minima(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for hashes in batches:
            yield pd.Series([None if h is None or not len(h) else ((np.asarray(h, "i8")[:, None] * a + c) % PRIME).min(0) for h in hashes])

    return minima


def fast_signature(tokens: Column, m: int, seed: str = "") -> Column:
    return signature_udf(m, seed)(token_hashes(tokens))


def band_texts(sig: Column, bands: int, width: int, label: str) -> Column:
    """One string per band: label, number and minima."""
    text = lambda i: F.concat(F.lit(label), F.lit(SEPARATOR), i.cast("string"), F.lit(SEPARATOR), F.array_join(F.slice(sig, i * width + 1, F.lit(width)).cast("array<string>"), "-"))
    return F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), text)


def lsh_probability(bands: Column, width: Column, j: Column) -> Column:
    """Chance that values of similarity j share a band."""
    return F.lit(1.0) - F.pow(F.lit(1.0) - F.pow(j, width), bands)


def threshold(bands: int, width: int) -> float:
    return (1 / bands) ** (1 / width)


def pick(target: float, hashes: int) -> tuple[int, int]:
    """(bands, width) with bands * width at most hashes whose threshold is closest to target; more bands on a tie."""
    return min(((b, w) for w in range(1, hashes + 1) for b in range(1, hashes // w + 1)), key=lambda x: (round(abs(threshold(*x) - target), 12), -x[0]))


def curve(points: DataFrame, settings, steps: int = 20) -> DataFrame:
    """b, w, j, docs and probability of every setting at the given points (step of ``steps``, docs)."""
    grid = F.explode(F.array(*[F.struct(F.lit(b).alias("b"), F.lit(w).alias("w")) for b, w in settings])).alias("g")
    j = F.col("step") / steps
    return points.select("step", "docs", grid).select("g.b", "g.w", j.alias("j"), "docs", lsh_probability(F.col("g.b"), F.col("g.w"), j).alias("prob"))
