"""Language-model scores from a hashed maximum-entropy model with a class-factored softmax.

A token's probability is that of its class given the context times that of the word given class and context. The
class is a softmax over hashed n-gram and skip features (the two classes before, the word before, the word
before that, both). The word is a softmax over its class: the log of its add-one count, and a weight for every pair
of the word before and the word that was seen, both of the head. Only such pairs change the sum over a class, so it
is known per word before and class, and no class is ever walked through. The weights of the most frequent pairs
travel with the model, the others are joined. Classes are learned from
counts of adjacent word endings, with the most frequent words as classes of their own and one class for a word
that repeats the one before. Counts cover every training token. Class weights are learned in rounds: every task
takes gradient steps from the shared weights over a slice of its texts and the changes are averaged row by row.
Pair weights are learned from the pairs' counts over all training texts, a task per group of words before: these
share no weight, so each task takes all steps on its own. How texts are split into tasks changes which steps are
averaged, and so class weights by a little; counts and pair weights do not depend on it.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import collect, release, settle_alone
from .common import settle

_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_MARKS = b".,;:!?%&*#$|\"'()"
END = b"\n"  # no word holds white space
ENDINGS, CLASSES, SINGLES = 512, 32, 8
BITS = (14, 14, 15)  # rows of the hashed features: word before, word before that, both
STARTS = np.cumsum([0, CLASSES**2, *(2**b for b in BITS)])
ROWS, BLOCK = int(STARTS[-1]), 512
_FIRST = 2 + SINGLES  # class 0: end, 1: repeat, then single words, then learned classes


def tokens(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class _Endings(dict):
    """Last four bytes of a word -> bucket of the last two before punctuation, and the punctuation's first."""

    def __missing__(self, tail: bytes) -> int:
        bare = tail.rstrip(_MARKS)
        if len(self) > 200_000:
            self.clear()
        self[tail] = bucket = zlib.crc32(bare[-2:] + b"|" + tail[len(bare) : len(bare) + 1]) % ENDINGS
        return bucket


_ENDINGS = _Endings()


@dataclass
class Classes:
    """Class of every word: a number per ending, and single words."""

    of_ending: np.ndarray
    singles: dict[bytes, int]
    head: dict[bytes, int]  # frequent word -> its place, from 1
    known: dict | None = None

    def packed(self) -> dict:
        """word -> hash, class and place in the head, in one integer. A worker's tasks share what it holds."""
        if self.known is None:
            self.known = _Known(self)
        return self.known

    def __getstate__(self) -> dict:
        return self.__dict__ | {"known": None}


class _Known(dict):
    def __init__(self, classes: Classes):
        super().__init__()
        self.class_of, self.singles, self.head = (_FIRST + classes.of_ending).tolist(), classes.singles, classes.head

    def __missing__(self, word: bytes) -> int:
        place = self.head.get(word, 0)
        c = self.singles.get(word) if place or not self.head else None  # single words are of the head, if there is one
        v = (zlib.crc32(word) << 28) | ((self.class_of[_ENDINGS[word[-4:]]] if c is None else c) << 20) | place
        if len(self) > 400_000:
            self.clear()
        self[word] = v
        return v


def learn_classes(adjacent: np.ndarray, many: int, steps: int = 30) -> np.ndarray:
    """Weighted k-means of endings on the roots of what stands before and after them."""
    weight = adjacent.sum(0) + adjacent.sum(1)
    rows = [np.sqrt(m / np.maximum(m.sum(1, keepdims=True), 1)) for m in (adjacent, adjacent.T)]
    x = np.hstack(rows)
    centre = x[np.argsort(-weight, kind="stable")[:many]].copy()
    near = np.zeros(len(x), int)
    for _ in range(steps):
        near = (np.square(centre).sum(1) - 2 * x @ centre.T).argmin(1)
        for j in range(many):
            w = weight * (near == j)
            if w.sum():
                centre[j] = w @ x / w.sum()
    return near


class _Numbered(dict):
    """word -> number in order of first sight; endings has each number's bucket."""

    def __init__(self) -> None:
        super().__init__()
        self.endings: list[int] = []

    def __missing__(self, word: bytes) -> int:
        self[word] = n = len(self)
        self.endings.append(_ENDINGS[word[-4:]])
        return n


def count_corpus(docs: DataFrame, most: int = 400_000) -> DataFrame:
    """(word, cell, n): training counts of every word and the end, and of every cell of adjacent endings. A task
    holds about ``most`` distinct words at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, counts, buckets = _Numbered(), np.zeros(0, "i8"), np.zeros(0, "i8")
        cells, texts_seen = np.zeros(ENDINGS**2, "i8"), 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(number), pa.binary()), pa.nulls(len(number), pa.int32()), pa.array(counts)], ["word", "cell", "n"])

        for batch in batches:
            lists = [tokens(t or b"") for t in batch.column(0).cast(pa.binary()).to_pylist()]
            texts_seen += len(lists)
            at = np.fromiter(map(number.__getitem__, chain.from_iterable(lists)), "i8", sum(map(len, lists)))
            buckets = np.append(buckets, number.endings[len(buckets) :])
            counts = np.append(counts, np.zeros(len(number) - len(counts), "i8")) + np.bincount(at, minlength=len(number))
            if len(at) > 1:
                near = buckets[at]
                pair = near[:-1] * ENDINGS + near[1:]
                lasts = np.cumsum([len(t) for t in lists])[:-1] - 1
                keep = np.ones(len(pair), bool)
                keep[lasts[(lasts >= 0) & (lasts < len(pair))]] = False
                cells += np.bincount(pair[keep], minlength=ENDINGS**2)
            if len(number) > most:
                yield out()
                number, counts, buckets = _Numbered(), np.zeros(0, "i8"), np.zeros(0, "i8")
        yield out()
        used = np.flatnonzero(cells)
        yield pa.RecordBatch.from_arrays([pa.nulls(len(used), pa.binary()), pa.array(used, pa.int32()), pa.array(cells[used], pa.int64())], ["word", "cell", "n"])
        yield pa.RecordBatch.from_arrays([pa.array([END], pa.binary()), pa.nulls(1, pa.int32()), pa.array([texts_seen], pa.int64())], ["word", "cell", "n"])

    made = docs.select("text").mapInArrow(run, "word binary, cell int, n long").filter("n > 0")
    return made.groupBy("word", "cell").agg(F.sum("n").alias("n"))


def context_rows(packed: np.ndarray, begins: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For the tokens of texts laid end to end, ends included: feature rows (n, 4), class to predict, class of
    the word. begins: where texts begin; what stands before a text is blank."""
    classes, hashes = ((packed >> 20) & 255).astype("i4"), (packed >> 28).astype("u8")

    def earlier(x: np.ndarray, by: int) -> np.ndarray:
        out = np.zeros_like(x)
        out[by:] = x[:-by]
        for k in range(by):
            at = begins + k
            out[at[at < len(x)]] = 0
        return out

    before, skip = earlier(hashes, 1), earlier(hashes, 2)
    near, far = earlier(classes, 1), earlier(classes, 2)
    first = begins[begins + 1 < len(packed)] + 1
    skip[first], far[first] = 0, 0
    repeat = hashes == before
    repeat[begins] = False
    target = np.where(repeat, np.int32(1), classes)
    rows = np.empty((len(packed), 4), "i4")
    rows[:, 0] = near * CLASSES + far
    mixed = (before * np.uint64(0x9E3779B97F4A7C15), skip * np.uint64(0xC2B2AE3D27D4EB4F), (before * np.uint64(0x165667B19E3779F9) + skip) * np.uint64(0x9E3779B97F4A7C15))
    for i, (m, b) in enumerate(zip(mixed, BITS, strict=True)):
        rows[:, i + 1] = (m >> np.uint64(64 - b)).astype("i4") + STARTS[i + 1]
    return rows, target, classes


def _stacked(texts: list[list[bytes]], known: dict) -> tuple:
    """context_rows of several texts, the packed words, where texts begin, and the words."""
    lengths = np.array([len(t) + 1 for t in texts])
    flat = []
    for t in texts:
        flat += t
        flat.append(END)
    packed = np.fromiter(map(known.__getitem__, flat), "i8", len(flat))
    begins = np.cumsum(lengths) - lengths
    return (*context_rows(packed, begins), packed, begins, flat)


PLACE = 2**20 - 1  # bits of a word's place in the head


def pair_keys(packed: np.ndarray, target: np.ndarray, begins: np.ndarray, blank: int) -> tuple[np.ndarray, np.ndarray]:
    """(where, keys) of the words that a learned class holds and that follow a word of the head: word before, class and
    word in one integer. The word's place is 0 if it is not of the head; a text's first word follows ``blank``."""
    before = np.empty_like(packed)
    before[1:] = packed[:-1] & PLACE
    before[begins] = blank
    where = np.flatnonzero((target >= _FIRST) & (before > 0))
    return where, (before[where] << 25) | (target[where].astype("i8") << 20) | (packed[where] & PLACE)


class _Pairs:
    """Counts of pair keys, emptied in parts by the group of the word before."""

    def __init__(self, groups: int):
        self.groups, self.held, self.many = groups, [], 0

    def add(self, keys: np.ndarray) -> None:
        self.held.append(keys)
        self.many += len(keys)

    def out(self, task: int) -> Iterator[pa.RecordBatch]:
        keys, counts = np.unique(np.concatenate(self.held), return_counts=True) if self.held else (np.empty(0, "i8"), np.empty(0, "i8"))
        self.held, self.many = [], 0
        group = (keys >> 25) % self.groups
        order = np.argsort(group, kind="stable")
        cuts = np.searchsorted(group[order], np.arange(self.groups + 1))
        for g in np.flatnonzero(np.diff(cuts)).tolist():
            at = order[cuts[g] : cuts[g + 1]]
            yield _change_row(task, -2 - g, keys[at].astype("<i8").tobytes(), counts[at].astype("<i8").tobytes())


def _change_row(task: int, block: int, change: bytes, touched: bytes) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"task": pa.array([task], pa.int64()), "block": pa.array([block], pa.int32()), "change": [change], "touched": [touched]})


def _summed(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pair keys and their counts over rows of packed ones."""
    keys, counts = (np.concatenate([np.frombuffer(x, "<i8") for x in pdf[c]]) for c in ("change", "touched"))
    order = np.argsort(keys, kind="stable")
    cuts = np.flatnonzero(np.append(True, np.diff(keys[order]) != 0))
    return keys[order][cuts], np.add.reduceat(counts[order], cuts)


def pair_weights(keys: np.ndarray, counts: np.ndarray, plain: np.ndarray, least: int, discount: float = 0.75, steps: int = 20) -> tuple[np.ndarray, np.ndarray]:
    """(keys, weights) of the pairs seen ``least`` times or more, and more often than the word's plain share lets expect
    even less the discount: the optimum of the likelihood under an absolute penalty. Steps go along the gradient of
    the log of a word's odds against the words of its class that have no weight here. plain: within-class share
    of each of the head's words by its count alone."""
    context = keys >> 20
    cuts = np.flatnonzero(np.append(True, np.diff(context) != 0))
    of = np.cumsum(np.append(0, np.diff(context) != 0))
    total = np.add.reduceat(counts, cuts).astype("f8")
    use = ((keys & PLACE) > 0) & (counts >= least) & (counts - discount > total[of] * plain[keys & PLACE])
    keys, of, seen = keys[use], of[use], counts[use] - discount
    share, weight = plain[keys & PLACE], np.zeros(len(keys))
    sums = lambda x: np.bincount(of, x, len(total))
    rest, rest_seen = 1 - sums(share), total - sums(seen)
    for _ in range(steps if len(keys) else 0):
        up = share * np.exp(weight)
        scale = total / (rest + sums(up))
        gradient = np.log(seen / (scale[of] * up)) - np.log(rest_seen / (scale * rest))[of]
        weight = np.clip(weight + 0.7 * gradient, 0, BOUND)
    return keys[weight > 0], weight[weight > 0]


def log_sums(at: np.ndarray, keys: np.ndarray, weights: np.ndarray, plain: np.ndarray, many: int) -> np.ndarray:
    """Log of the sum over the class for each of ``many`` contexts, of pairs and the contexts that they are at."""
    return np.log1p(np.bincount(at, plain[keys & PLACE] * np.expm1(weights), many)).astype("f4")


class PairTable:
    """Pair weights by hash, four places to a bucket, and the log of each context's sum by its number. A key is mixed by
    an odd factor, which loses nothing: its high bits are the bucket and the rest is kept, so no other key is taken
    for it. The lightest of a bucket that is too full stand in a sorted list beside the table. log_sum, if given, is of more
    pairs than are held here, which looked_up() tells."""

    KEY_BITS, FACTOR = 42, 0x9E3779B97F5
    NONE = 0xFFFFFFFF

    def __init__(self, keys: np.ndarray, weights: np.ndarray, plain: np.ndarray, log_sum: np.ndarray | None = None):
        self.bits = max(11, int(len(keys)).bit_length())
        bucket, tag = self._mixed(keys)
        order = np.lexsort((-weights, bucket))
        cuts = np.flatnonzero(np.append(True, np.diff(bucket[order]) != 0)) if len(keys) else np.empty(0, "i8")
        nth = np.arange(len(keys)) - np.repeat(cuts, np.diff(np.append(cuts, len(keys))))
        beyond = order[nth >= 4]
        self.full = np.zeros(2**self.bits, bool)
        self.full[bucket[beyond]] = True
        beyond = beyond[np.argsort(keys[beyond])]
        self.beyond, self.beyond_values = keys[beyond], weights[beyond].astype("f4")
        held, nth = order[nth < 4], nth[nth < 4]
        tags, self.values = np.full((2**self.bits, 4), self.NONE, "u4"), np.zeros(2**self.bits * 4, "f4")
        tags[bucket[held], nth] = tag[held]
        self.values[bucket[held] * 4 + nth] = weights[held]
        self.tags = tags.reshape(-1).view("c16")  # a bucket is read as one number
        self.log_sum = log_sums(keys >> 20, keys, weights, plain, len(plain) * 32) if log_sum is None else log_sum

    def _mixed(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        mixed = (keys.astype("u8") * np.uint64(self.FACTOR)) & np.uint64(2**self.KEY_BITS - 1)
        rest = np.uint64(self.KEY_BITS - self.bits)
        return (mixed >> rest).astype("i8"), (mixed & ((np.uint64(1) << rest) - np.uint64(1))).astype("u4")

    def log_factor(self, keys: np.ndarray) -> np.ndarray:
        """What the context adds to the log of a word's plain share: its pair's weight less the log of the sum."""
        return self.looked_up(keys)[0]

    def looked_up(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """log_factor() by the pairs held here, and the places of the keys that only a pair held elsewhere can change."""
        out = -self.log_sum.take(keys >> 20)
        some = np.flatnonzero((out < 0) & ((keys & PLACE) > 0))
        bucket, tag = self._mixed(keys[some])
        hit = np.flatnonzero(self.tags.take(bucket).view("u4").reshape(-1, 4) == tag[:, None])
        out[some[hit >> 2]] += self.values.take((bucket[hit >> 2] << 2) + (hit & 3))
        missed = np.ones(len(some), bool)
        missed[hit >> 2] = False
        if len(self.beyond):
            full = np.flatnonzero(self.full.take(bucket))
            rest = some[full]
            at = np.minimum(np.searchsorted(self.beyond, keys[rest]), len(self.beyond) - 1)
            found = self.beyond[at] == keys[rest]
            out[rest[found]] += self.beyond_values[at[found]]
            missed[full[found]] = False
        return out, some[missed]


#: Weights stay within this bound, so sums of four and a bias can be exponentiated as they are.
BOUND = 12.0
_ONES = np.ones(CLASSES, "f4")


def _logits(weights: np.ndarray, bias: np.ndarray, rows: np.ndarray) -> np.ndarray:
    z = weights.take(rows[:, 0], 0)
    for k in range(1, rows.shape[1]):
        z += weights.take(rows[:, k], 0)
    z += bias
    return z


def gradient_steps(weights: np.ndarray, seen: np.ndarray, bias: np.ndarray, rows: np.ndarray, target: np.ndarray, rate: float) -> None:
    """One step over a batch, in place. A row's step shrinks with the root of how often it was seen."""
    p = _logits(weights, bias, rows)
    np.exp(p, out=p)
    p /= (p @ _ONES)[:, None]
    p[np.arange(len(target)), target] -= 1
    bias -= 0.05 * p.mean(0)
    np.clip(bias, -BOUND, BOUND, out=bias)
    by_class = np.ascontiguousarray(p.T)
    for k in range(rows.shape[1]):
        near = (rows[:, k] - STARTS[k]).astype("u2")  # 16-bit numbers are sorted by counting
        order = near.argsort(kind="stable")
        at = near[order]
        fresh = np.append(True, at[1:] != at[:-1])
        place = np.empty(len(at), "i8")
        place[order] = np.cumsum(fresh) - 1
        one, many = at[fresh] + STARTS[k], np.bincount(place).astype("f4")
        seen[one] += many
        total = np.empty((len(one), CLASSES), "f4")
        for c, gradient in enumerate(by_class):
            total[:, c] = np.bincount(place, gradient)
        total *= (rate / np.sqrt(seen[one] * many)).astype("f4")[:, None]
        np.subtract(weights.take(one, 0), total, out=total)
        weights[one] = np.clip(total, -BOUND, BOUND, out=total)


def _changes(docs: DataFrame, model: dict, classes, rate: float, groups: int, batch_tokens: int = 8_000, most_pairs: int = 4_000_000) -> DataFrame:
    """(task, block, change, touched): what a task's steps did to the blocks of rows it met; block -1: biases; below:
    the keys and counts of pairs, by group. Changes are bounded, so they travel as half floats; how often a row
    was met is exact."""
    shipped = docs.sparkSession.sparkContext.broadcast({k: model[k] for k in ("weights", "seen", "bias")})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, task = shipped.value, TaskContext.get().partitionId()
        weights, seen, bias = m["weights"].astype("f4"), m["seen"].copy(), m["bias"].copy()
        known, pairs, held, size, total = classes.value.packed(), _Pairs(groups), [], 0, 0
        blank = known[END] & PLACE

        def steps() -> None:
            rows, target, _, packed, begins, _ = _stacked(held, known)
            for i in range(0, len(rows), 2 * batch_tokens):
                gradient_steps(weights, seen, bias, rows[i : i + 2 * batch_tokens], target[i : i + 2 * batch_tokens], rate)
            pairs.add(pair_keys(packed, target, begins, blank)[1])

        for batch in batches:
            for text in batch.column(0).cast(pa.binary()).to_pylist():
                held.append(tokens(text or b""))
                size += len(held[-1]) + 1
                if size >= batch_tokens:
                    steps()
                    total, held, size = total + size, [], 0
            if pairs.many > most_pairs:
                yield from pairs.out(task)
        if held:
            steps()
            total += size
        if not total:
            return
        yield from pairs.out(task)
        touched = seen - m["seen"]
        for b in range(-(-ROWS // BLOCK)):
            t = touched[b * BLOCK : (b + 1) * BLOCK]
            if t.any():
                change = weights[b * BLOCK : (b + 1) * BLOCK] - m["weights"][b * BLOCK : (b + 1) * BLOCK]
                yield _change_row(task, b, change.astype("<f2").tobytes(), t.astype("<f4").tobytes())
        yield _change_row(task, -1, (bias - m["bias"]).astype("<f2").tobytes(), np.array([total], "<f4").tobytes())

    return docs.select("text").mapInArrow(run, "task long, block int, change binary, touched binary")


def _averaged(pdf: pd.DataFrame) -> pd.DataFrame:
    """Changes of one block, each row weighted by how often its task met it; pairs of one group are added up."""
    if pdf.block.iloc[0] < -1:
        keys, counts = _summed(pdf)
        return pd.DataFrame({"task": [int(pdf.task.iloc[0])], "block": [int(pdf.block.iloc[0])], "change": [keys.tobytes()], "touched": [counts.tobytes()]})
    touched = [np.frombuffer(x, "<f4") for x in pdf.touched]
    many = sum(touched)
    change = sum(np.frombuffer(c, "<f2").astype("f4").reshape(len(t), -1) * t[:, None] for c, t in zip(pdf.change, touched, strict=True)) / np.maximum(many, 1)[:, None]
    return pd.DataFrame({"task": [int(pdf.task.iloc[0])], "block": [int(pdf.block.iloc[0])], "change": [change.astype("<f2").tobytes()], "touched": [many.astype("<f4").tobytes()]})


def one_round(docs: DataFrame, model: dict, classes, rate: float, tasks: int, groups: int, fan_in: int = 32) -> tuple[dict, DataFrame]:
    """The model after one round, and the table of its changes, which has its pairs. Changes are averaged in groups of
    fan_in tasks until one row a block is left."""
    changes, width = _changes(docs.coalesce(tasks), model, classes, rate, groups), tasks
    while width > 1:
        changes = changes.withColumn("task", F.floor(F.col("task") / fan_in)).groupBy("task", "block").applyInPandas(_averaged, "task long, block int, change binary, touched binary")
        width = -(-width // fan_in)
    changes = settle(changes, "round")
    weights, seen, bias = model["weights"].copy(), model["seen"].copy(), model["bias"].copy()
    for r in changes.filter("block >= -1").collect():  # as many rows as the model has blocks
        change, touched = np.frombuffer(r["change"], "<f2"), np.frombuffer(r["touched"], "<f4")
        if r["block"] < 0:
            bias = bias + change.astype("f4")
        else:
            at = slice(r["block"] * BLOCK, r["block"] * BLOCK + len(touched))
            weights[at] += change.reshape(-1, CLASSES)
            seen[at] += touched
    return model | {"weights": weights, "seen": seen, "bias": bias}, changes


def learn_pairs(pairs: DataFrame, plain: np.ndarray, most: int, groups: int) -> tuple[PairTable, DataFrame]:
    """Weights of all pairs (block, change, touched: a group's keys and counts). The most frequent up to ``most``, all that
    are seen as often as the last of them or none of these, are held by the table, with the sums of every context; the
    others are rows (key, weight)."""

    def levels(pdf: pd.DataFrame) -> pd.DataFrame:
        keys, counts = _summed(pdf)
        level, many = np.unique(np.minimum(counts[(keys & PLACE) > 0], 100_000), return_counts=True)
        return pd.DataFrame({"level": level, "many": many})

    least, room = 2**62, most
    for r in sorted(pairs.groupBy("block").applyInPandas(levels, "level long, many long").groupBy("level").agg(F.sum("many").alias("many")).collect(), reverse=True):
        if r["many"] > room:
            break
        least, room = r["level"], room - r["many"]
    shipped = pairs.sparkSession.sparkContext.broadcast(plain)

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        plain, group, (keys, counts) = shipped.value, -2 - int(pdf.block.iloc[0]), _summed(pdf)
        found, weights = pair_weights(keys, counts, plain, 1)
        at = ((found >> 25) - group) // groups * 32 + (found >> 20 & 31)  # place among the contexts of the group
        sums = log_sums(at, found, weights, plain, 32 * len(range(group, len(plain), groups)))
        often = counts[np.searchsorted(keys, found)] >= least
        made = pd.DataFrame({"group": pd.array([None] * len(found), "Int64"), "key": found, "weight": weights, "often": often, "sums": None})
        return pd.concat([pd.DataFrame({"group": pd.array([group], "Int64"), "key": [0], "weight": [0.0], "often": [False], "sums": [sums.tobytes()]}), made])

    made = settle(pairs.groupBy("block").applyInPandas(fit, "group long, key long, weight double, often boolean, sums binary"), "pairs")
    log_sum = np.zeros((len(plain), 32), "f4")
    for r in made.filter("group IS NOT NULL").select("group", "sums").collect():  # 128 bytes per word of the head in all
        log_sum[r["group"] :: groups] = np.frombuffer(r["sums"], "f4").reshape(-1, 32)
    held = made.filter("often").select("key", "weight").toArrow()  # most pairs at most
    keys, weights = (held.column(c).to_numpy() for c in ("key", "weight"))
    order = np.argsort(keys)
    return PairTable(keys[order], weights[order], plain, log_sum.ravel()), made.filter("group IS NULL AND NOT often").select("key", "weight")


def train(docs: DataFrame, head_words: int = 120_000, most_pairs: int = 262_144, slices: int = 4, rate: float = 0.3, tokens_per_task: int = 20_000_000) -> dict:
    """Fit on docs (doc_id, text). Counts, classes and normalisers take in every token; round r takes gradient
    steps and counts pairs over the slice r of ``slices`` by id hash, so that all rounds visit every text once.
    ``head_words`` and ``most_pairs`` bound what travels with the model; all other words stay in the table "counts", all
    other pairs in the table "far", null if there are none.
    Null and empty texts are one end token each, repeated rows count as often as they stand there, a null id is hashed
    as the empty text; without rows every weight is 0 and every probability that of no counts."""
    if head_words >= 2**17:
        raise ValueError("a word of the head is numbered in 17 bits")
    counts = settle(count_corpus(docs), "counts")
    words = counts.filter("word IS NOT NULL").select("word", "n")
    n, v = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    adjacent = np.zeros(ENDINGS**2)
    for r in counts.filter("cell IS NOT NULL").select("cell", "n").collect():  # ENDINGS squared rows at most
        adjacent[r["cell"]] = r["n"]
    levels = words.groupBy(F.least("n", F.lit(10_000)).alias("level")).count().collect()
    least, room = 10_000, head_words
    for level, many in sorted(levels, reverse=True):
        if many > room:
            break
        least, room = level, room - many
    head = {bytes(r["word"]): i + 1 for i, r in enumerate(words.filter(F.col("n") >= least).orderBy("word").collect())} if room < head_words else {}
    singles = [bytes(r["word"]) for r in words.filter(F.col("word") != END).orderBy(F.desc("n"), "word").limit(SINGLES).collect()]
    classes = Classes(learn_classes(adjacent.reshape(ENDINGS, ENDINGS), CLASSES - _FIRST), {END: 0} | {w: 2 + i for i, w in enumerate(singles)}, head)
    shipped = docs.sparkSession.sparkContext.broadcast(classes)

    def by_class(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, total, distinct = shipped.value.packed(), np.zeros(CLASSES, "i8"), np.zeros(CLASSES, "i8")
        for batch in batches:
            at = np.array([known[w] >> 20 & 255 for w in batch.column(0).to_pylist()], "i8")
            total += np.bincount(at, batch.column(1).to_numpy(), CLASSES).astype("i8")
            distinct += np.bincount(at, minlength=CLASSES)
        yield pa.RecordBatch.from_arrays([pa.array(range(CLASSES), pa.int32()), pa.array(total), pa.array(distinct)], ["class", "n", "v"])

    total, distinct = np.zeros(CLASSES, "i8"), np.zeros(CLASSES, "i8")
    for r in words.mapInArrow(by_class, "class int, n long, v long").groupBy("class").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect():
        total[r["class"]], distinct[r["class"]] = r["n"], r["v"]
    counted = np.ones(len(head) + 1, "i8")
    for r in words.filter(F.col("n") >= least).collect() if head else []:
        counted[head[bytes(r["word"])]] = r["n"]
    start = np.maximum(np.log((total + 1) / (total.sum() + CLASSES)), -BOUND).astype("f4")
    start[1] = np.log(0.01)
    model = {"classes": classes, "n": int(n), "v": int(v), "class_n": total, "class_v": distinct, "head_counts": counted, "weights": np.zeros((ROWS, CLASSES), "f4"), "seen": np.full(ROWS, 1.0, "f4"), "bias": start}
    place_class = np.zeros(len(head) + 1, "i8")
    known = classes.packed()
    for w, place in head.items():
        place_class[place] = known[w] >> 20 & 255
    plain = (counted + 1) / (total + distinct + 1)[place_class]
    tasks, groups, made = max(12, -(-int(n) // tokens_per_task)), min(4096, max(64, -(-int(n) // tokens_per_task))), []  # a group's pairs are bounded by the head
    for r in range(slices if n else 0):
        part = docs.filter(F.pmod(F.xxhash64(F.lit("slice"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(slices)) == r)
        model, changes = one_round(part, model, shipped, rate, tasks, groups)
        made.append(changes)
    pairs = [changes.filter("block < -1").select("block", "change", "touched") for changes in made]
    table, far = learn_pairs(reduce(DataFrame.unionByName, pairs), plain, most_pairs, groups) if pairs else (PairTable(np.empty(0, "i8"), np.empty(0), plain), None)
    for changes in made:  # what is learned from them is written
        release(changes)
    collect(docs.sparkSession)
    return model | {"counts": words, "pairs": table, "far": far if far is not None and far.limit(1).count() else None}


#: Shares of the keys that are joined one after another: what is shuffled for one is deleted before the next.
SHARES = 4


def _paired(made: DataFrame, others: DataFrame, share: int) -> DataFrame:
    """(row, b, m, k): what a share of the pairs (key, weight) adds to the rows whose texts hold them."""
    mine = lambda key: F.pmod(F.xxhash64(key), F.lit(SHARES)) == share
    asked = made.select("row", F.explode(F.filter("far", mine)).alias("key"))
    sums = asked.join(others.filter(mine(F.col("key"))), "key").groupBy("row").agg(F.sum("weight").alias("w"))
    return sums.select("row", F.lit(0.0).alias("b"), (F.col("w") / float(np.log(10))).alias("m"), F.lit(0).cast("long").alias("k"))


def score(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score and score of every row. Null counts as empty: one end
    token. Words outside the head and pairs outside the table are looked up by joins and added; ids may repeat."""
    counts, others = model["counts"], model["far"]
    join_pairs = others is not None
    n, v, class_n, class_v = model["n"], model["v"], model["class_n"], model["class_v"]
    shipped = docs.sparkSession.sparkContext.broadcast({k: model[k] for k in ("classes", "head_counts", "weights", "bias", "class_n", "class_v", "pairs")})
    schema = f"row long, doc_id {docs.schema[id_col].dataType.simpleString()}, n_tokens long, n_known long, base double, model double, rare array<struct<word:binary,class:int,n:long>>, far array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        known, task, row = m["classes"].packed(), TaskContext.get().partitionId(), 0
        head = np.log10(m["head_counts"] + 1.0)
        spread = np.log10(m["class_n"] + m["class_v"] + 1.0)
        spread[1] = 0
        blank = known[END] & PLACE
        plain = np.arange(CLASSES) >= _FIRST
        for batch in batches:
            texts = batch.column(1).cast(pa.binary()).to_pylist()
            i = 0
            while i < len(texts):
                begin, lists, size = i, [], 0
                while i < len(texts) and size < 20_000:
                    lists.append(tokens(texts[i] or b""))
                    size, i = size + len(lists[-1]) + 1, i + 1
                rows, target, _, packed, begins, flat = _stacked(lists, known)
                lp = np.empty(len(target))
                for a in range(0, len(target), 4_000):  # what is worked on stays in the cache
                    z = _logits(m["weights"], m["bias"], rows[a : a + 4_000])
                    chosen = z[np.arange(len(z)), target[a : a + 4_000]]
                    lp[a : a + 4_000] = chosen - np.log(np.exp(z, out=z) @ _ONES)
                where, keys = pair_keys(packed, target, begins, blank)
                factor, missed = m["pairs"].looked_up(keys)
                lp[where] += factor
                missed = missed[: len(missed) if join_pairs else 0]
                place = packed & PLACE
                inside = plain[target]  # end, repeat and single words need no second factor
                lp = lp / np.log(10) - np.where(inside, spread[target], 0) + np.where(inside & (place > 0), head[place], 0)
                ends = np.cumsum([len(x) + 1 for x in lists])
                sums = lambda x: np.diff(np.append(0.0, np.cumsum(x))[np.append(0, ends)])
                # Words outside the head, repeats in a row as one with their number.
                missing = np.flatnonzero(place == 0)
                owner = np.searchsorted(ends, missing, "right")
                fresh = np.ones(len(missing), bool)
                fresh[1:] = (packed[missing[1:]] != packed[missing[:-1]]) | (target[missing[1:]] != target[missing[:-1]]) | (owner[1:] != owner[:-1])
                first = missing[fresh]
                struct = pa.StructArray.from_arrays(
                    [pa.array([flat[j] for j in first.tolist()], pa.binary()), pa.array(target[first], pa.int32()), pa.array(np.diff(np.append(np.flatnonzero(fresh), len(missing))), pa.int64())], ["word", "class", "n"]
                )
                rare = pa.ListArray.from_arrays(pa.array(np.searchsorted(owner[fresh], np.arange(len(lists) + 1)), pa.int32()), struct)
                far = pa.ListArray.from_arrays(pa.array(np.searchsorted(where[missed], np.append(0, ends)), pa.int32()), pa.array(keys[missed]))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array((task << 40) + row + np.arange(len(lists)), pa.int64()), batch.column(0).slice(begin, len(lists)), pa.array(np.diff(np.append(0, ends)), pa.int64()),
                        pa.array(np.rint(sums((place > 0).astype("f8"))), pa.float64()).cast(pa.int64()), pa.array(sums(np.where(place > 0, head[place], 0))), pa.array(sums(lp)), rare, far,
                    ],
                    ["row", "doc_id", "n_tokens", "n_known", "base", "model", "rare", "far"],
                )
                row += len(lists)

    made = settle(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema), "scores")
    looked = made.select("row", F.inline("rare")).join(counts.withColumnRenamed("n", "c"), "word", "left")
    log = F.log10(F.coalesce("c", F.lit(0)) + F.lit(1.0))
    found = looked.select("row", (F.col("n") * log).alias("b"), F.when(F.col("class") >= _FIRST, F.col("n") * log).otherwise(0.0).alias("m"), F.when(F.col("c") > 0, F.col("n")).otherwise(0).alias("k"))
    for i in range(SHARES if join_pairs else 0):
        found = found.unionByName(settle_alone(docs.sparkSession, lambda i=i: _paired(made, others, i), "paired"))
    extra = found.groupBy("row").agg(F.sum("b").alias("more_base"), F.sum("m").alias("more_model"), F.sum("k").alias("more_known"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    return made.drop("rare", "far").join(extra, "row", "left").select(
        "doc_id", "n_tokens", (F.col("n_known") + zero("more_known")).cast("long").alias("n_known"), F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + zero("more_base") - F.col("n_tokens") * F.lit(float(np.log10(n + v + 1)))).alias("base_score"), (F.col("model") + zero("more_model")).alias("score"),
    )
