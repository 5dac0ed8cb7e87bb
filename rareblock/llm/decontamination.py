"""Benchmark decontamination over a distributed positional inverted index.

The index is sharded by document: a shard holds whole documents, laid end to end with a gap, and for each
term the sorted list of its positions. It is stored as Parquet in the shared folder, one row per shard of
bounded size. Phrases are sought in every shard by intersecting offset-adjusted posting lists, beginning
with the shard's rarest term. A shard looks up each of the benchmark's terms once; the phrases that have all
their terms in the shard are then found by array operations, and only these are intersected. The phrases travel
in blocks of bounded size; a larger benchmark takes more blocks, not a larger broadcast.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

#: Bytes kept inside words after A-Z is lower-cased: digits, a-z and all of a multi-byte character.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))

GAP = 64  # positions between two documents, more than any proximity may span


def words_of(text: bytes) -> list[bytes]:
    """Words of lower-cased text: runs of digits, letters a-z and characters beyond ASCII."""
    return text.translate(_FOLD).split()


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shard_words: int = 250_000) -> DataFrame:
    """The stored index: shard, docs (ids in order), n_words and starts (int32 arrays as bytes), terms,
    ends and positions. A null text has no words. A shard ends with the document that passes shard_words."""
    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"shard string, docs array<{id_type}>, n_words binary, starts binary, terms array<binary>, ends binary, positions binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, made = TaskContext.get().partitionId(), 0
        ids, counts, chunks, held, vocabulary, id_arrow = [], [], [], 0, defaultdict(), None

        def shard() -> pa.RecordBatch:
            n_words = np.array(counts, "<i4")
            starts = (np.cumsum(n_words + GAP) - n_words - GAP).astype("<i4")
            local = np.concatenate(chunks) if chunks else np.empty(0, "i4")
            where = np.arange(len(local), dtype="i4") + np.repeat(np.arange(len(counts), dtype="i4") * GAP, n_words)
            positions = where[np.argsort(local, kind="stable")].astype("<i4")
            ends = np.cumsum(np.bincount(local, minlength=len(vocabulary))).astype("<i4")
            one = lambda v, t: pa.array([v], t)
            return pa.RecordBatch.from_arrays(
                [one(f"{task:07d}-{made:05d}", pa.string()), one(ids, pa.list_(id_arrow)), one(n_words.tobytes(), pa.binary()), one(starts.tobytes(), pa.binary()), one(list(vocabulary), pa.list_(pa.binary())), one(ends.tobytes(), pa.binary()), one(positions.tobytes(), pa.binary())],
                ["shard", "docs", "n_words", "starts", "terms", "ends", "positions"],
            )

        for batch in batches:
            id_arrow = batch.schema.field(0).type
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
                words = words_of(text or b"")
                vocabulary.default_factory = vocabulary.__len__
                chunks.append(np.array([vocabulary[w] for w in words], "i4"))
                ids.append(doc_id), counts.append(len(words))
                held += len(words) + GAP
                if held >= shard_words:
                    yield shard()
                    made, held = made + 1, 0
                    ids, counts, chunks, vocabulary = [], [], [], defaultdict()
        if ids:
            yield shard()

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


class Shard:
    """One shard's posting lists."""

    def __init__(self, n_words: bytes, starts: bytes, terms: list[bytes], ends: bytes, positions: bytes):
        self.n_words, self.starts = np.frombuffer(n_words, "<i4"), np.frombuffer(starts, "<i4")
        self.ends, self.positions = np.frombuffer(ends, "<i4"), np.frombuffer(positions, "<i4")
        self.number = {t: i for i, t in enumerate(terms)}

    def postings(self, term: bytes) -> np.ndarray:
        i = self.number.get(term)
        return self.positions[:0] if i is None else self.positions[self.ends[i - 1] if i else 0 : self.ends[i]]

    def phrase(self, words: tuple[bytes, ...]) -> np.ndarray:
        """Positions at which the words stand one after another."""
        lists = []
        for offset, word in enumerate(words):
            found = self.postings(word)
            if not len(found):
                return found
            lists.append((len(found), offset, found))
        lists.sort(key=lambda x: x[:2])
        _, offset, found = lists[0]
        begins = found - offset
        for n, offset, found in lists[1:]:
            at = np.searchsorted(found, begins + offset)
            begins = begins[(at < n) & (found[np.minimum(at, n - 1)] == begins + offset)]
            if not len(begins):
                break
        return begins

    def near(self, words: tuple[bytes, ...], slop: int) -> list[tuple[int, int]]:
        """Spans [begin, end) of the rarest word's postings round which each other distinct word stands
        within slop positions, in any order."""
        lists = sorted((self.postings(w) for w in set(words)), key=len)
        if not lists or not len(lists[0]):
            return []
        low, high = lists[0].copy(), lists[0] + 1
        keep = np.ones(len(low), bool)
        for found in lists[1:]:
            if not len(found):
                return []
            at = np.searchsorted(found, lists[0])
            before, after = found[np.maximum(at - 1, 0)], found[np.minimum(at, len(found) - 1)]
            ok_b, ok_a = np.abs(lists[0] - before) <= slop, np.abs(after - lists[0]) <= slop
            nearest = np.where(ok_a & (~ok_b | (np.abs(after - lists[0]) < np.abs(lists[0] - before))), after, before)
            keep &= ok_a | ok_b
            low, high = np.minimum(low, nearest), np.maximum(high, nearest + 1)
        return [(int(a), int(b)) for a, b in zip(low[keep], high[keep], strict=True)]


def windows_of(words: list[bytes], size: int) -> set[tuple[bytes, ...]]:
    """All runs of size words; a shorter item is one run; no words, no run."""
    return {tuple(words[i : i + size]) for i in range(max(1, len(words) - size + 1))} if words else set()


@dataclass
class Phrases:
    """Distinct phrases of a block of items as rows of term numbers."""

    terms: list[bytes]
    grid: np.ndarray  # (phrases, longest), -1 after a phrase's end
    owners: list[list[str]]  # the items of each phrase

    @classmethod
    def of(cls, items: list[tuple[object, bytes]], window: int) -> Phrases:
        found: dict[tuple[bytes, ...], list[str]] = defaultdict(list)
        for item, text in items:
            for run in windows_of(words_of(text or b""), window):
                found[run].append(str(item))
        number: defaultdict[bytes, int] = defaultdict()
        number.default_factory = number.__len__
        grid = np.full((len(found), max(map(len, found), default=1)), -1, "i4")
        for row, run in zip(grid, found, strict=True):
            row[: len(run)] = [number[w] for w in run]
        return cls(list(number), grid, list(found.values()))

    def possible(self, shard: Shard, rows: int = 100_000) -> Iterator[tuple[tuple[bytes, ...], list[str]]]:
        """The phrases all of whose terms are in the shard, with their items."""
        there = np.array([t in shard.number for t in self.terms] + [True])  # -1 reads the last
        for start in range(0, len(self.grid), rows):
            for p in (np.flatnonzero(there[self.grid[start : start + rows]].all(1)) + start).tolist():
                yield tuple(self.terms[t] for t in self.grid[p].tolist() if t >= 0), self.owners[p]


def search(index: DataFrame, items: list[tuple[object, bytes]], window: int = 10, slop: int | None = None, only_hit: bool = False) -> DataFrame:
    """One row per indexed document, or with ``only_hit`` per document that is hit, from one block of items: shard,
    place, doc_id, n_words, spans (merged word ranges that are hit) and items (their ids as strings). slop None:
    exact phrases of ``window`` words; else proximity: every word of the window within slop positions of its
    rarest one."""
    if slop is not None and 2 * slop >= GAP:
        raise ValueError(f"slop must be below {GAP // 2}")
    shipped = index.sparkSession.sparkContext.broadcast(Phrases.of(items, window))
    id_type = index.schema["docs"].dataType.elementType.simpleString()
    schema = f"shard string, place int, doc_id {id_type}, n_words long, spans array<struct<begin:int,stop:int>>, items array<string>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = {name: batch.column(name)[i] for name in batch.schema.names}
                shard = Shard(*(row[k].as_py() for k in ("n_words", "starts", "terms", "ends", "positions")))
                spans, items_of = defaultdict(list), defaultdict(set)
                for words, owners in shipped.value.possible(shard):
                    found = [(int(b), int(b) + len(words)) for b in shard.phrase(words)] if slop is None else shard.near(words, slop)
                    for begin, stop in found:
                        d = int(np.searchsorted(shard.starts, begin, "right")) - 1
                        spans[d].append((begin - int(shard.starts[d]), stop - int(shard.starts[d])))
                        items_of[d].update(owners)
                places = sorted(spans) if only_hit else range(len(shard.n_words))
                at = np.array(places, "i8")
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([row["shard"].as_py()] * len(at), pa.string()), pa.array(at, pa.int32()), row["docs"].values.take(pa.array(at)), pa.array(shard.n_words[at].astype("i8")),
                        pa.array([[{"begin": b, "stop": e} for b, e in merged(spans[d])] if d in spans else [] for d in places], pa.list_(pa.struct([("begin", pa.int32()), ("stop", pa.int32())]))),
                        pa.array([sorted(items_of[d]) if d in spans else [] for d in places], pa.list_(pa.string())),
                    ],
                    ["shard", "place", "doc_id", "n_words", "spans", "items"],
                )

    return index.mapInArrow(run, schema)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for begin, stop in sorted(spans):
        if out and begin <= out[-1][1]:
            out[-1] = (out[-1][0], max(stop, out[-1][1]))
        else:
            out.append((begin, stop))
    return out


def covered(spans: Column) -> Column:
    """Positions inside any of the spans."""
    start = F.struct(F.lit(0).alias("upto"), F.lit(0).cast("long").alias("n"))
    add = lambda acc, s: F.struct(F.greatest(acc["upto"], s["stop"]).alias("upto"), (acc["n"] + F.greatest(F.lit(0), s["stop"] - F.greatest(s["begin"], acc["upto"]))).alias("n"))
    return F.aggregate(F.array_sort(spans), start, add, lambda acc: acc["n"])


def find_contamination(docs: DataFrame, benchmark: DataFrame, window: int = 10, slop: int | None = None, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", block_bytes: int = 4_000_000) -> DataFrame:
    """One row per document: doc_id, n_words, spans, items. Null texts and ids are allowed; repeated rows give
    repeated results; with an empty benchmark no document is hit. Items go out in blocks of about
    ``block_bytes`` of text, each collected and broadcast alone; the first returns all documents, later ones
    those that they hit."""
    index = settle(build_index(docs, id_col, text_col), "postings")
    items = benchmark.select(F.col(item_col).alias("item"), F.coalesce(F.col(item_text_col), F.lit("")).cast("binary").alias("text"))
    total = items.agg(F.coalesce(F.sum(F.octet_length("text") + 64), F.lit(0))).first()[0]
    blocks = max(1, -(-total // block_bytes))
    parts = []
    for b in range(blocks):
        chosen = items if blocks == 1 else items.filter(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == b)
        parts.append(settle(search(index, [(r["item"], bytes(r["text"])) for r in chosen.collect()], window, slop, only_hit=b > 0), "hits", batch_rows=2))
    if blocks == 1:
        return parts[0].select("doc_id", "n_words", "spans", "items")
    found = parts[0]
    for part in parts[1:]:
        found = found.unionByName(part)
    return (
        found.groupBy("shard", "place")
        .agg(F.first("doc_id").alias("doc_id"), F.first("n_words").alias("n_words"), F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
        .select("doc_id", "n_words", "spans", "items")
    )


def digest(found: DataFrame) -> DataFrame:
    return found.select(
        "doc_id", "n_words", covered(F.col("spans")).alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ","), 256).alias("items_sha256"), (F.size("spans") > 0).alias("contaminated"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", **how) -> DataFrame:
    """The documents no window of the benchmark occurs in, all columns. A row is judged by its own text, whatever
    its id, so null and repeated ids lose nothing; rows of one text have one verdict. A null text stays."""
    content = F.md5(docs[text_col].cast("binary"))
    hit = find_contamination(docs.select(content.alias("content"), F.col(text_col).alias("text")), benchmark, id_col="content", **how)
    hit = hit.filter("size(spans) > 0").select("doc_id").distinct()
    return docs.join(hit, content == hit["doc_id"], "left_anti")
