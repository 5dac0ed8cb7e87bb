"""Best-fit packing planned over a length histogram.

Tokenising emits only (length, rank within length and task). A histogram of at most ``seq_len`` rows is
packed best-fit-decreasing on the driver as runs of equal decisions, so the plan's size depends on the
number of lengths and not on the corpus. Pieces then find their slot by a join on length and rank range.
"""

from __future__ import annotations

import bisect
import json
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import settle

#: Fixed value: the public pre-tokenisation pattern of this byte-level vocabulary.
WORD_PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

PLAN_SCHEMA = "length int, rank_from long, rank_to long, first_sequence long, per_sequence long, at long"


def byte_level_encoder(vocabulary_path: str):
    """A tiktoken encoder with the vocabulary of a byte-level BPE file of the tokenizers library."""
    import tiktoken

    with open(vocabulary_path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    shown = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(plain))}
    ranks = {bytes(shown[c] for c in word): rank for word, rank in vocabulary.items() if all(c in shown for c in word) and not word.startswith("<|")}
    return tiktoken.Encoding("byte_level", pat_str=WORD_PATTERN, mergeable_ranks=ranks, special_tokens={})


def cut(n: int, seq_len: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n ids: full ones, and a shorter one in front if n is no multiple."""
    first = n % seq_len
    return [(0, first)] * bool(first) + [(s, seq_len) for s in range(first, n, seq_len)]


def token_pieces(docs: DataFrame, vocabulary_path: str, seq_len: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, and (task, local_rank), which number the
    pieces of one length within a task. A null text counts as empty and still has its end id."""
    schema = f"doc_id {docs.schema[id_col].dataType.simpleString()}, piece int, start long, length int, ids_crc32 long, task int, local_rank long" + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = byte_level_encoder(vocabulary_path)
        task, seen = TaskContext.get().partitionId(), np.zeros(seq_len + 1, "i8")
        for batch in batches:
            at, piece, start, length, crc, rank, kept = [], [], [], [], [], [], []
            for i, text in enumerate(batch.column(1).to_pylist()):
                ids = np.asarray(encoder.encode_ordinary(text or "") + [end_id], "<u4")
                for k, (s, n) in enumerate(cut(len(ids), seq_len)):
                    part = ids[s : s + n]
                    at.append(i), piece.append(k), start.append(s), length.append(n), crc.append(zlib.crc32(part.tobytes())), rank.append(seen[n])
                    seen[n] += 1
                    if with_ids:
                        kept.append(part.astype("i4"))
            columns = [batch.column(0).take(pa.array(at, "i4")), pa.array(piece, "i4"), pa.array(start, "i8"), pa.array(length, "i4"), pa.array(crc, "i8"), pa.array([task] * len(at), "i4"), pa.array(rank, "i8")]
            yield pa.RecordBatch.from_arrays(columns + [pa.array(kept, pa.list_(pa.int32()))] * with_ids, ["doc_id", "piece", "start", "length", "ids_crc32", "task", "local_rank"] + ["ids"] * with_ids)

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


def plan_best_fit(histogram: dict[int, int], seq_len: int) -> list[tuple[int, int, int, int, int, int]]:
    """Best-fit-decreasing over counts. A run (length, rank_from, rank_to, first_sequence, per_sequence, at)
    puts items rank_from .. rank_to - 1 of that length into consecutive sequences, per_sequence in each,
    beginning at token ``at`` of each sequence."""
    room: dict[int, list[tuple[int, int]]] = defaultdict(list)  # space left -> blocks of (first sequence, how many)
    spaces: list[int] = []
    runs, opened = [], 0

    def give_back(space: int, first: int, many: int) -> None:
        if space and many:
            if not room[space]:
                bisect.insort(spaces, space)
            room[space].append((first, many))

    for length in sorted((n for n, c in histogram.items() if c), reverse=True):
        left, rank = histogram[length], 0
        while left:
            i = bisect.bisect_left(spaces, length)
            if i < len(spaces):
                space = spaces[i]
                first, many = room[space].pop()
                if not room[space]:
                    spaces.pop(i)
            else:
                space, first, many = seq_len, opened, -(-left // (seq_len // length))
                opened += many
            each = space // length
            whole = min(many, left // each)
            if whole:
                runs.append((length, rank, rank + whole * each, first, each, seq_len - space))
                give_back(space - each * length, first, whole)
                rank, left = rank + whole * each, left - whole * each
            if whole < many and left:
                runs.append((length, rank, rank + left, first + whole, left, seq_len - space))
                give_back(space - left * length, first + whole, 1)
                rank, left, whole = rank + left, 0, whole + 1
            give_back(space, first + whole, many - whole)
    return runs


def pack(docs: DataFrame, vocabulary_path: str, seq_len: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """All documents in sequences of at most seq_len ids: doc_id, piece, start, length, ids_crc32,
    sequence_id, offset (and ids). Repeated rows are packed as often as they occur; an empty table gives no rows."""
    pieces = settle(token_pieces(docs, vocabulary_path, seq_len, end_id, id_col, text_col, with_ids), "pieces")
    counts = pieces.groupBy("length", "task").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("length", "task", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # seq_len rows at most
    plan = docs.sparkSession.createDataFrame(plan_best_fit(histogram, seq_len), PLAN_SCHEMA)
    ranked = pieces.join(bases, ["length", "task"]).withColumn("rank", F.col("base") + F.col("local_rank"))
    slots = F.broadcast(plan.withColumnRenamed("length", "planned"))
    placed = ranked.join(slots, (F.col("length") == F.col("planned")) & (F.col("rank") >= F.col("rank_from")) & (F.col("rank") < F.col("rank_to")))
    nth = F.col("rank") - F.col("rank_from")
    return placed.select(
        "doc_id", "piece", "start", F.col("length").cast("long").alias("length"), "ids_crc32",
        (F.col("first_sequence") + F.floor(nth / F.col("per_sequence"))).alias("sequence_id"),
        (F.col("at") + (nth % F.col("per_sequence")) * F.col("length")).alias("offset"),
        *["ids"] * with_ids,
    )


def sequences(packed: DataFrame) -> DataFrame:
    """The packed sequences themselves, from pack(with_ids=True): sequence_id, n_pieces, ids in place order.
    A group holds at most seq_len ids."""
    inside = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(F.count("*").alias("n_pieces"), F.flatten(F.transform(inside, lambda p: p["ids"])).alias("ids"))
