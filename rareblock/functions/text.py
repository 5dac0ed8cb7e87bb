"""Normalisation and tokens as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}]+"
_ACCENTED = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ"
_PLAIN = "aaaaaaceeeeiiiinooooouuuuyy"


def normalise(c: Column, lower: bool = True, trim: bool = True, squash_ws: bool = True, strip_accents: bool = False, strip_punct: bool = False) -> Column:
    """The string that is hashed: null stays null."""
    if lower:
        c = F.lower(c)
    if strip_accents:
        c = F.translate(c, _ACCENTED, _PLAIN)
    if strip_punct:
        c = F.regexp_replace(c, r"[^\p{L}\p{N}\s]", "")
    if squash_ws:
        c = F.regexp_replace(c, r"\s+", " ")
    return F.trim(c) if trim else c


def word_list(c: Column) -> Column:
    """Words in order, repeats kept."""
    return F.regexp_extract_all(F.lower(c), F.lit(WORD), F.lit(0))


def words(c: Column) -> Column:
    """Distinct words."""
    return F.array_distinct(word_list(c))


def _let(value: Column, then) -> Column:
    """then(value), value being computed once, where a lambda would compute it for every element."""
    return F.element_at(F.transform(F.array(value), then), 1)


def word_ngrams(c: Column, n: int) -> Column:
    """Distinct runs of n words; none if there are fewer."""

    def runs(w: Column) -> Column:
        made = F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, F.lit(n)), " "))
        return F.when(F.size(w) >= n, F.array_distinct(made)).otherwise(F.array().cast("array<string>"))

    return _let(word_list(c), runs)


def qgrams(c: Column, q: int) -> Column:
    """Distinct runs of q characters of the lower-cased string."""
    low = F.lower(c)
    runs = F.transform(F.sequence(F.lit(1), F.length(low) - (q - 1)), lambda i: F.substring(low, i, F.lit(q)))
    return F.when(F.length(low) >= q, F.array_distinct(runs)).otherwise(F.array().cast("array<string>"))


def strip_html(c: Column) -> Column:
    """Text between tags, scripts and styles left out, five common references decoded, white space squashed."""
    c = F.regexp_replace(c, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    c = F.regexp_replace(c, r"(?s)<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        c = F.replace(c, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(c, r"\s+", " "))


def canonical_url(c: Column) -> Column:
    """Lower-case URL without scheme, leading www., query, fragment and trailing slashes."""
    c = F.regexp_replace(F.lower(c), r"[?#].*$", "")
    return F.regexp_replace(F.regexp_replace(c, r"^[a-z]+://(www\.)?", ""), r"/+$", "")


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two arrays of distinct values; 0 if both are empty."""
    common = F.size(F.array_intersect(a, b))
    every = F.size(a) + F.size(b) - common
    return F.when(every > 0, common / every).otherwise(F.lit(0.0))
