"""Block building: from attributes to the inverted index of a record's keys.

The index has one row per record, (rid, keys array<binary>); attributes end here. Building it is one
projection. Null, empty and token-less values make no key, else they would form one giant block.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import minhash, text
from ..functions.hashing import key_of

_NO_KEYS = "array<binary>"


@dataclass(frozen=True)
class KeySpec:
    """A block-building function: keys(how, null_as_value) is a column of array<binary>, each key once."""

    name: str
    keys: Callable[[str, bool], Column]


def rendered(c: Column, dtype: T.DataType | None = None) -> Column:
    """A value as text: nested values as JSON, timestamps and others by cast."""
    if isinstance(dtype, (T.ArrayType, T.MapType, T.StructType)):
        return F.to_json(c)
    return c.cast("string")


def _one(key: Column) -> Column:
    return F.when(key.isNotNull(), F.array(key)).otherwise(F.array().cast(_NO_KEYS))


def identity(value: str | Column, attribute: str | None = None, normalise: Callable[[Column], Column] | None = None, dtype: T.DataType | None = None) -> KeySpec:
    """One key from attribute name and normalised value: equal text in two attributes gives two keys."""
    c = F.col(value) if isinstance(value, str) else value
    label = attribute or value
    clean = normalise or (lambda x: F.trim(F.lower(x)))

    def keys(how: str, null_as_value: bool) -> Column:
        v = clean(rendered(c, dtype))
        v = F.coalesce(v, F.lit("")) if null_as_value else F.when(v != "", v)
        return _one(key_of([F.lit(label), v], how))

    return KeySpec(f"identity({label})", keys)


def token(columns: list[str | Column], tokenizer: Callable[[Column], Column] = text.words) -> KeySpec:
    """Every distinct token of any of the columns is a key, without the attribute: one key wherever it stands."""
    cols = [F.col(c) if isinstance(c, str) else c for c in columns]

    def keys(how: str, null_as_value: bool) -> Column:
        every = F.array_distinct(F.flatten(F.array(*[F.coalesce(tokenizer(c), F.array().cast("array<string>")) for c in cols])))
        return F.transform(F.filter(every, lambda t: t != ""), lambda t: key_of([t], how))

    return KeySpec("token", keys)


def lsh(value: str | Column, attribute: str, bands: int, width: int, tokenizer: Callable[[Column], Column] = text.words, seed: str = "", share_attribute: bool = False, fast: bool | None = None) -> KeySpec:
    """One key per band of a MinHash signature. share_attribute drops the attribute from the key, so that bands
    of two columns may meet on purpose. fast computes the same minima with numpy over Arrow batches: by default
    from nine hashes on, where that beats one pass over the tokens per hash."""
    c = F.col(value) if isinstance(value, str) else value
    fast = bands * width > 8 if fast is None else fast

    def keys(how: str, null_as_value: bool) -> Column:
        sig = (minhash.fast_signature if fast else minhash.signature)(tokenizer(c), bands * width, seed)
        texts = F.element_at(F.transform(F.array(sig), lambda s: minhash.band_texts(s, bands, width, "" if share_attribute else attribute)), 1)
        return F.when(sig.isNotNull(), F.transform(texts, lambda t: key_of([t], how))).otherwise(F.array().cast(_NO_KEYS))

    return KeySpec(f"lsh({attribute},{bands},{width})", keys)


def build_index(df: DataFrame, rid: str | Column, specs: list[KeySpec], how: str = "md5", null_as_value: bool = False, keep: tuple[Column, ...] = ()) -> DataFrame:
    """(rid, keys): a record's distinct keys over all specs, and what it keeps beside. Records without a key or an id are left out.
    Works on any number of columns, of any name; only those of the specs are read."""
    r = F.col(rid) if isinstance(rid, str) else rid
    made = [s.keys(how, null_as_value) for s in specs]  # distinct in themselves; binary values are made distinct by comparing all
    keys = made[0] if len(made) == 1 else F.array_distinct(F.flatten(F.array(*made)))
    return df.select(r.cast("bigint").alias("rid"), keys.alias("keys"), *keep).filter("rid IS NOT NULL AND size(keys) > 0")


def postings(index: DataFrame) -> DataFrame:
    """(rid, key), one row per entry of the index."""
    return index.select("rid", F.explode("keys").alias("key"))


def from_long(df: DataFrame, rid: str, key: str) -> DataFrame:
    """The index of a table of (record, key) rows, repeats and nulls dropped."""
    return df.select(F.col(rid).cast("bigint").alias("rid"), F.col(key).cast("binary").alias("key")).filter("rid IS NOT NULL AND key IS NOT NULL").groupBy("rid").agg(F.collect_set("key").alias("keys"))


def autospec(df: DataFrame, rid: str, bands: int = 6, width: int = 7) -> list[KeySpec]:
    """Identity keys for every column but rid, banded keys for strings whose mean over all rows is above two words."""
    strings = [f.name for f in df.schema.fields if isinstance(f.dataType, T.StringType) and f.name != rid]
    means = df.agg(*[F.avg(F.size(text.words(F.col(s)))).alias(s) for s in strings]).first() if strings else {}
    return [
        lsh(f.name, f.name, bands, width) if f.name in strings and (means[f.name] or 0) > 2 else identity(f.name, dtype=f.dataType)
        for f in df.schema.fields
        if f.name != rid
    ]
