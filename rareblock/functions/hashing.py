"""128-bit keys and 64-bit id hashes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SEPARATOR = "\u001f"


def key_of(parts: list[Column], how: str = "md5") -> Column:
    """BINARY(16) of the parts joined by a unit separator. A null part makes a null key."""
    joined = F.concat(*[x for p in parts for x in (p, F.lit(SEPARATOR))][:-1])
    if how == "md5":
        return F.unhex(F.md5(joined.cast("binary")))
    lane = lambda seed: F.lpad(F.hex(F.xxhash64(F.lit(seed), joined)), 16, "0")
    return F.when(joined.isNotNull(), F.unhex(F.concat(lane(1), lane(2))))


def child_key(a: Column, b: Column, how: str = "md5") -> Column:
    """Key of the intersection of two blocks, a before b in byte order. 'h64' is of keys that are 64-bit numbers."""
    if how == "h64":
        return F.xxhash64(a, b)
    both = F.concat(a, b)
    if how == "md5":
        return F.unhex(F.md5(both))
    lane = lambda seed: F.lpad(F.hex(F.xxhash64(F.lit(seed), both)), 16, "0")
    return F.unhex(F.concat(lane(1), lane(2)))


def printed(key: Column) -> Column:
    return F.lower(F.hex(key))


def md5_bits(c: Column, digits: int = 15) -> Column:
    """First digits of the md5 as a number: 60 bits at most, so that it fits a BIGINT."""
    return F.conv(F.substring(F.md5(c.cast("string").cast("binary")), 1, digits), 16, 10).cast("bigint")
