"""SpotSigs fingerprints: chains of content words that follow common words.

A common word (an anchor) opens a chain of the next content words; the hash of anchor and chain is a
signature, and a text's fingerprint is the set of them. Furniture around an article has few common words and
so few signatures. Sets are compared by Jaccard similarity; a join first parts them by size and indexes only
the rarest signatures that a similar set cannot all lack.
"""

from __future__ import annotations

import base64
import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import settle

# Common words of English, German, French and Spanish, which open chains.
ANCHORS = frozenset(
    "a an and are as at be by for from in is it of on or that the this to was with "
    "auf das dem den der des die ein eine ist mit nicht sich und von zu "
    "au aux dans de des du en est et la le les par pas pour que qui sur un une "
    "al como con del el las los no para por se su una y".split()
)
_STOP = frozenset(w.encode() for w in ANCHORS)
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)
_OPENING = np.uint64(0x5851F42D4C957F2D)


class _Marked(defaultdict):
    """Word to 64-bit hash, odd for anchors."""

    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word) & ~1 | (word in _STOP)
        return h


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def signature_sets(texts: list[str], chain: int = 2, distance: int = 1, hashes: dict | None = None) -> list[np.ndarray]:
    """Sorted distinct 32-bit signatures of each text. The beginning of a text counts as an anchor; a chain is
    cut short by the end; every ``distance``-th content word is taken. A text whose words are all anchors has
    one signature, of them all; a text without a word has one of its characters; an empty text has none."""
    hashes = _Marked() if hashes is None else hashes
    lists = [t.encode().translate(_FOLD).split() for t in texts]
    lengths = np.array([len(x) for x in lists], "i8")
    words = np.array([hashes[w] for x in lists for w in x], "u8")
    ends = np.cumsum(lengths)
    begins = ends - lengths
    opens = (words & np.uint64(1)).astype(bool)
    content = np.append(np.flatnonzero(~opens), len(words) + np.arange(chain * distance + 1))  # padding ends every search
    owner = np.repeat(np.arange(len(lists)), lengths)
    at = np.concatenate([np.flatnonzero(opens), begins[lengths > 0]])
    whose = np.concatenate([owner[opens], np.flatnonzero(lengths > 0)])
    h = np.concatenate([_mix(words[opens]), np.full(int((lengths > 0).sum()), _OPENING)])
    first = np.searchsorted(content, at)
    reached = np.zeros(len(at), bool)
    padded = np.append(words, np.zeros(content[-1] + 1 - len(words), "u8"))
    for c in range(chain):
        place = content[np.minimum(first + c * distance, len(content) - 1)]
        inside = place < ends[whose] if len(whose) else np.zeros(0, bool)
        h = np.where(inside, _mix(h + padded[place] + _GOLDEN), h)
        reached |= inside
    h, whose = (h[reached] >> np.uint64(32)).astype("<u4"), whose[reached]
    order = np.lexsort((h, whose))
    h, whose = h[order], whose[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (whose[1:] != whose[:-1])
    h, whose = h[new], whose[new]
    cuts = np.searchsorted(whose, np.arange(len(lists) + 1))
    out = [h[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    for i, (s, text) in enumerate(zip(out, texts, strict=True)):
        if not len(s) and text:
            out[i] = np.array([xxhash.xxh32_intdigest(b" ".join(lists[i]) or text.encode())], "<u4")
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard similarity; two empty sets are alike."""
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    common = len(np.intersect1d(a, b, assume_unique=True))
    return common / (len(a) + len(b) - common)


def printed(signatures: np.ndarray) -> str:
    return base64.b64encode(signatures.tobytes()).decode()


def edited_text(text: str, following: str) -> str:
    """text with its last half of code points replaced by as many first ones of the following text."""
    k = len(text) // 2
    return text[: len(text) - k] + following[:k]


def _ranges(docs: DataFrame, parts: int) -> list:
    """Ascending bounds that cut the ids, of any type with an order, into about equal parts; ids alone are sorted."""
    if parts < 2:
        return []
    ids = docs.filter("doc_id IS NOT NULL").select("doc_id").repartitionByRange(parts, "doc_id")
    return sorted(r["least"] for r in ids.groupBy(F.spark_partition_id()).agg(F.min("doc_id").alias("least")).collect())[1:]  # a row per range


def _above(column: Column, bounds: list) -> Column:
    """How many bounds are at most the value, by halving."""
    if not bounds:
        return F.lit(0)
    array, start = F.array(*[F.lit(b) for b in bounds]), F.struct(F.lit(0).alias("lo"), F.lit(len(bounds)).alias("hi"))

    def halve(acc: Column, _: Column) -> Column:
        middle = F.floor((acc["lo"] + acc["hi"]) / 2).cast("int")
        up = F.get(array, middle) <= column
        open_ = acc["lo"] < acc["hi"]
        return F.struct(F.when(open_ & up, middle + 1).otherwise(acc["lo"]).alias("lo"), F.when(open_ & ~up, middle).otherwise(acc["hi"]).alias("hi"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(len(bounds).bit_length())), start, halve, lambda acc: acc["lo"])


def with_following(docs: DataFrame, run, schema: str, part_bytes: int = 16_000_000, least_parts: int = 8, most_parts: int = 16_384) -> DataFrame:
    """run(texts, ids, following texts) over the rows in descending order of doc_id, each with the text of the
    row after it, the last with that of the first. The texts are shuffled once, a task per range of ids of about
    ``part_bytes`` (larger beyond ``most_parts`` ranges); the first row of each range is found by its id alone and
    sent to the range before. Equal ids are ordered by content hash and text; null ids come last, and as they may
    be many, in ranges of the hash."""
    content = F.xxhash64("text")
    rows, nulls, size = docs.agg(F.count("*"), F.count_if(F.col("doc_id").isNull()), F.sum(F.octet_length("text"))).first()
    if not rows:
        return docs.sparkSession.createDataFrame([], schema)
    parts = min(most_parts, max(least_parts, -(-size // part_bytes)))
    bounds = _ranges(docs, parts)
    null_parts = -(-nulls * parts // rows)
    null_part = F.floor((content / F.lit(2.0**64) + 0.5) * null_parts)
    part = F.when(F.col("doc_id").isNull(), len(bounds) + 1 + F.least(null_part, F.lit(max(0, null_parts - 1)))).otherwise(F.lit(len(bounds)) - _above(F.col("doc_id"), bounds))
    ranged = docs.select("doc_id", "text", part.cast("int").alias("part"), F.when(F.col("doc_id").isNull(), content).alias("hash"))
    heads = {r["part"]: (r["id"], r["hash"]) for r in ranged.groupBy("part").agg(F.max("doc_id").alias("id"), F.min("hash").alias("hash")).collect()}  # a row per range
    present = sorted(heads)
    before = {p: present[i - 1] for i, p in enumerate(present)}
    targets = docs.sparkSession.createDataFrame([(p, *heads[p], before[p]) for p in present], f"head_part int, head_id {docs.schema['doc_id'].dataType.simpleString()}, head_hash long, to_part int")
    at_head = (F.col("part") == F.col("head_part")) & F.col("doc_id").eqNullSafe(F.col("head_id")) & F.col("hash").eqNullSafe(F.col("head_hash"))
    # Of the rows of a range's first id, the first: least content hash, then least text.
    firsts = ranged.join(F.broadcast(targets), at_head).groupBy("to_part").agg(F.min(F.struct(content.alias("c"), F.col("text"))).alias("f"), F.first("doc_id").alias("doc_id"))
    firsts = firsts.select("doc_id", F.col("f.text").alias("text"), F.col("to_part").alias("part"), F.lit(1).alias("edge"))
    both = ranged.select("doc_id", "text", "part", F.lit(0).alias("edge")).unionByName(firsts)
    ordered = both.repartitionById(max(present) + 1, "part").sortWithinPartitions("part", "edge", F.col("doc_id").desc_nulls_last(), F.xxhash64("text"), "text")

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            kind = batch.schema.field(0).type
            for start in range(0, batch.num_rows, 400):
                held += zip(*(batch.column(i).slice(start, 400).to_pylist() for i in range(4)), strict=True)
                if len(held) > 1:
                    yield from run(held, kind)
                    held = held[-1:]

    return ordered.select("doc_id", "text", "part", "edge").mapInArrow(go, schema)


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chain: int = 2, distance: int = 1, **how) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited and near_next of every row.
    The edited text is edited_text() with the next row's. A null text counts as empty; an empty text's
    fingerprint is empty and like another empty one only. Ids may be of any type with an order, null or repeated.
    ``how`` goes to with_following()."""
    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"doc_id {id_type}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def run(rows: list[tuple], kind: pa.DataType) -> Iterator[pa.RecordBatch]:
        hashes = _Marked()
        texts = [r[1] for r in rows]
        sets = signature_sets(texts, chain, distance, hashes)
        use = [i for i in range(len(rows) - 1) if not rows[i][3] and rows[i + 1][2] == rows[i][2]]
        edited = [edited_text(texts[i], texts[i + 1]) for i in use]
        changed = signature_sets(edited, chain, distance, hashes)
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([rows[i][0] for i in use], kind), pa.array([len(texts[i]) for i in use], pa.int64()),
                pa.array([hashlib.sha256(e.encode()).hexdigest() for e in edited], pa.string()),
                pa.array([printed(sets[i]) for i in use], pa.string()), pa.array([printed(s) for s in changed], pa.string()),
                pa.array([likeness(sets[i], s) for i, s in zip(use, changed, strict=True)], pa.float64()),
                pa.array([likeness(sets[i], sets[i + 1]) for i in use], pa.float64()),
            ],
            ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
        )

    named = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return with_following(named, run, schema, **how)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chain: int = 2, distance: int = 1) -> DataFrame:
    """doc_id, signatures (array of int, sorted) and n_signatures of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 400):
                part = batch.slice(start, 400)
                sets = signature_sets([t or "" for t in part.column(1).to_pylist()], chain, distance)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([np.sort(s.astype("i4")) for s in sets], pa.list_(pa.int32())), pa.array([len(s) for s in sets], pa.int32())], ["doc_id", "signatures", "n_signatures"])

    made = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    return made.mapInArrow(run, f"doc_id {docs.schema[id_col].dataType.simpleString()}, signatures array<int>, n_signatures int")


def size_part(n, least: float):
    """Number of a set's size range; sets at least ``least`` alike are in one range or in neighbouring ones."""
    return F.floor(F.log(n.cast("double")) / F.lit(-float(np.log(least)))).cast("int")


def matches(prints: DataFrame, least: float = 0.8) -> DataFrame:
    """Pairs (a, b, jaccard) of classes of equal fingerprints, a < b, at least ``least`` alike; a class goes by
    its least doc_id, and prints joined on signatures gives the members. Texts without signatures match none.

    Each set offers its rarest signatures, 1 + floor((1 - least) * size) of them: alike sets share one. Pairs
    meet inside a size range or between neighbours, and sizes too unlike are dropped before sets are read."""
    classes = settle(prints.filter("n_signatures > 0 AND doc_id IS NOT NULL").groupBy("signatures").agg(F.min("doc_id").alias("doc_id"), F.first("n_signatures").alias("n")), "prints")
    tokens = classes.select("doc_id", "n", F.explode("signatures").alias("signature"))
    spread = tokens.groupBy("signature").agg(F.count("*").alias("df")).filter("df > 1")
    rarity = Window.partitionBy("doc_id").orderBy("df", "signature")
    # Signatures of one set only come first in rarity and can match nothing: they use up the offer.
    single = F.col("n") - F.count("*").over(Window.partitionBy("doc_id"))
    offered = tokens.join(spread, "signature").withColumns({"nth": F.row_number().over(rarity), "single": single})
    offered = offered.filter(F.col("nth") + F.col("single") <= 1 + F.floor((1 - least) * F.col("n") + 1e-9)).select("doc_id", "n", "signature", size_part(F.col("n"), least).alias("range"))
    x = offered.withColumn("range", F.explode(F.array("range", F.col("range") + 1))).alias("x")
    y = offered.alias("y")
    on = (F.col("x.signature") == F.col("y.signature")) & (F.col("x.range") == F.col("y.range")) & (F.col("x.doc_id") != F.col("y.doc_id")) & (F.col("x.n") <= F.col("y.n")) & (F.col("x.n") >= F.lit(least) * F.col("y.n") - 1e-9)
    pairs = x.join(y, on).select(F.least("x.doc_id", "y.doc_id").alias("a"), F.greatest("x.doc_id", "y.doc_id").alias("b")).distinct()
    side = lambda name: classes.select(F.col("doc_id").alias(name), F.col("signatures").alias(f"s{name}"))
    common = F.size(F.array_intersect("sa", "sb"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").withColumn("jaccard", common / (F.size("sa") + F.size("sb") - common))
    return both.filter(F.col("jaccard") >= least - 1e-12).select("a", "b", "jaccard")
