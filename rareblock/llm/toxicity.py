"""Toxicity by a subsequence string kernel, Nyström landmarks and a support vector machine.

Two words are compared by the triples of characters they share in order, gaps allowed: a triple that spans
s characters weighs DECAY ** s, so an inserted or replaced character lowers the likeness a little and does not
end it. Landmark words give Nyström features, a squared-hinge machine separates words of toxic sentences
from words of clean ones, and its decision, being linear in the triples, is laid out as one lookup table.
A sentence is as toxic as its worst word, a text as its worst sentence.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle

SPAN, DECAY, CODES = 5, 0.6, 64
_LETTERS = {c: i + 1 for i, c in enumerate("abcdefghijklmnopqrstuvwxyz0123456789")} | {"^": 37, "$": 38}
_EDGE = re.compile(r"^[^\w]+|[^\w]+$")
_LONE = re.compile(r"(?<!\w)\w(?:[^\w\n]{1,2}\w){3,}(?!\w)")
_SENTENCE = re.compile(r"[.!?\n]+(?=\s|$)")
#: Offsets of the characters after the first, for subsequences of three and of four.
_STEPS = [(a, b) for b in range(2, SPAN + 1) for a in range(1, b)] + [(a, b, c) for c in range(3, SPAN + 1) for b in range(2, c) for a in range(1, b)]
#: One slot per triple; those of four characters are hashed behind them.
SLOTS = CODES**3 + 2**20
#: A word that follows so many different words in toxic sentences and none in clean ones is no chance.
SURE = 10


def _code(c: str) -> int:
    """Letters and digits have codes of their own, other letters share 25; punctuation is a gap."""
    return _LETTERS.get(c) or (39 + ord(c) % 25 if c.isalpha() else 0)


class _Codes(dict):
    def __missing__(self, c: str) -> int:
        self[c] = v = _code(c)
        return v


_CODES = _Codes()


def words_in(sentence: str) -> list[str]:
    """Lower-case words without outer punctuation, and runs of single characters joined to a word."""
    low = sentence.lower()
    words = [w if w.isalnum() else _EDGE.sub("", w) for w in low.split()]
    return words + [re.sub(r"[^\w]+", "", m[0]) for m in _LONE.finditer(low)]


def _laid(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes of all words with borders, gaps of SPAN zeros between them; where each begins; its norm."""
    sizes = np.array([len(w) + 2 for w in words])
    starts = np.cumsum(sizes + SPAN) - sizes - SPAN
    codes = np.zeros(int((sizes + SPAN).sum()), "i8")
    flat = np.fromiter((_CODES[c] for w in words for c in f"^{w}$"), "i8", int(sizes.sum()))
    codes[np.repeat(starts, sizes) + np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = flat
    square = np.zeros(len(words))
    for step in _STEPS:
        square += np.maximum(sizes - step[-1], 0) * DECAY ** (2 * step[-1])
    return codes, starts, np.sqrt(np.maximum(square, 1e-9))


def _slots(codes: np.ndarray) -> Iterator[tuple[np.ndarray, float]]:
    """For each choice of gaps, the slot of the subsequence that begins at each place, 0 if it meets a gap."""
    n = len(codes) - SPAN
    for step in _STEPS:
        slot, whole = codes[:n], codes[:n] > 0
        for offset in step:
            slot = slot * CODES + codes[offset : n + offset]
            whole = whole & (codes[offset : n + offset] > 0)
        if len(step) == 3:
            slot = CODES**3 + ((slot * 0x9E3779B1 >> 17) & (2**20 - 1))
        yield np.where(whole, slot, 0), DECAY ** step[-1]


def kernel_table(words: list[str], weights: np.ndarray) -> np.ndarray:
    """Sum of the weighted, normed subsequence vectors of words, as a table over slots."""
    codes, starts, norms = _laid(words)
    each = np.repeat(weights / norms, np.diff(np.append(starts, len(codes))))
    table = np.zeros(SLOTS)
    for slot, decay in _slots(codes):
        np.add.at(table, slot, decay * each[: len(slot)])
    table[0] = 0
    return table


def decisions(words: list[str], table: np.ndarray) -> np.ndarray:
    """The table's value for each word: its kernel with the weighted words in the table."""
    if not words:
        return np.empty(0)
    codes, starts, norms = _laid(words)
    total = np.zeros(len(codes))
    for slot, decay in _slots(codes):
        total[: len(slot)] += decay * table[slot]
    return np.add.reduceat(total, starts) / norms


def kernels(words: list[str], marks: list[str], at_once: int = 64) -> np.ndarray:
    """Kernels of all words with all marks, over the slots that some mark has. ``at_once`` marks are laid out together,
    which bounds the dense arrays by their slots instead of all marks'."""
    out = np.empty((len(words), len(marks)), "f4")
    where = np.zeros(SLOTS, "i4")
    for first in range(0, len(marks), at_once):
        vectors = []
        for m in marks[first : first + at_once]:
            codes, starts, norms = _laid([m])
            found: Counter = Counter()
            for slot, decay in _slots(codes):
                for x in slot.tolist():
                    found[x] += decay / norms[0]
            found.pop(0, None)
            vectors.append(found)
        used = sorted(set().union(*vectors)) or [0]
        where[:] = 0
        where[used] = np.arange(1, len(used) + 1)
        dense = np.zeros((len(used) + 1, len(vectors)), "f4")
        for j, found in enumerate(vectors):
            dense[where[list(found)], j] = list(found.values())
        for i in range(0, len(words), 500):
            codes, starts, norms = _laid(words[i : i + 500])
            vector = np.zeros((len(norms), len(used) + 1), "f4")
            owner = np.repeat(np.arange(len(norms)), np.diff(np.append(starts, len(codes))))
            for slot, decay in _slots(codes):
                np.add.at(vector, (owner[: len(slot)], where[slot]), decay)
            vector[:, 0] = 0
            out[i : i + 500, first : first + at_once] = (vector @ dense) / norms[:, None]
    return out


def fit_machine(positive: list[str], negative: list[str], weight: np.ndarray, landmarks: int = 700, penalty: float = 0.003) -> tuple[np.ndarray, float]:
    """(table, bias) of the machine that separates the words, each positive one weighing ``weight``. Nyström:
    features are kernels with the landmarks, whitened by the inverse root of the landmarks' own kernels."""
    marks = list(dict.fromkeys(positive[: landmarks // 2] + negative[: landmarks // 2]))
    words = positive + negative
    between, own = kernels(words, marks), kernels(marks, marks).astype("f8")
    values, vectors = np.linalg.eigh((own + own.T) / 2)
    keep = values > 1e-6 * values.max()
    whiten = vectors[:, keep] / np.sqrt(values[keep])
    x = np.ones((len(words), whiten.shape[1] + 1))
    spans = [slice(i, i + 1000) for i in range(0, len(words), 1000)]  # no second copy of all features
    for span in spans:
        x[span, :-1] = between[span].astype("f8") @ whiten
    del between
    y = np.r_[np.ones(len(positive)), -np.ones(len(negative))]
    share = np.r_[0.2 * weight / max(1e-9, weight.sum()), np.full(len(negative), 0.8 / max(1, len(negative)))]
    w = np.zeros(x.shape[1])
    ridge = np.full(len(w), penalty / 2)
    ridge[-1] = 1e-6
    for _ in range(30):  # Newton steps over the margin violators
        inside = y * (x @ w) < 1
        square, side = np.diag(ridge), np.zeros(len(w))
        for span in spans:
            xs = x[span][inside[span]]
            weighed = (xs * share[span][inside[span], None]).T
            square += weighed @ xs
            side += weighed @ y[span][inside[span]]
        new = np.linalg.solve(square, side)
        if np.allclose(new, w, atol=1e-9):
            break
        w = new
    return kernel_table(marks, whiten @ w[:-1]), float(w[-1])


class Scorer:
    """Worst word of each text; values of words are remembered."""

    def __init__(self, table: np.ndarray, bias: float, remember: int = 1_000_000):
        self.table, self.bias, self.remember, self.known = table, bias, remember, {}

    def worst(self, texts: list[str]) -> list[tuple[float, str]]:
        lists = [{w for s in (t,) for w in words_in(s)} - {""} for t in texts]
        new = [w for w in set().union(*lists) if w not in self.known]
        if len(self.known) + len(new) > self.remember:
            self.known = {}
            new = list(set().union(*lists))
        for i in range(0, len(new), 50_000):
            part = new[i : i + 50_000]
            self.known.update(zip(part, (decisions(part, self.table) + self.bias).tolist(), strict=True))
        known = self.known
        return [max(((known[w], w) for w in words), default=(self.bias - 1.0, "")) for words in lists]


def _labelled(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """Rows (text, label) of a bounded sample: the labelled ids of least hash, about max_rows of them. An id counts
    once, with its least text."""
    n = labels.count()
    if n > max_rows:
        labels = labels.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * max_rows / n))
    once = docs.join(F.broadcast(labels), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("label").alias("label"))
    return once.select("text", "label")  # max_rows ids at most


def _word_counts(sample: DataFrame) -> DataFrame:
    """word, toxic (distinct words it follows in toxic sentences: copies of a text count once) and clean
    (sentences of clean texts it occurs in)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            toxic, clean = set(), Counter()
            for text, label in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for sentence in _SENTENCE.split(text or ""):
                    words = words_in(sentence)
                    if label:
                        toxic.update(zip(words, ["", *words], strict=False))
                    else:
                        clean.update(set(words))
            pairs = list(toxic)
            yield pa.RecordBatch.from_arrays(
                [pa.array([w for w, _ in pairs] + list(clean), pa.string()), pa.array([p for _, p in pairs] + [None] * len(clean), pa.string()), pa.array([0] * len(pairs) + list(clean.values()), pa.int64())], ["word", "before", "clean"]
            )

    made = sample.mapInArrow(run, "word string, before string, clean long").filter("word <> ''")
    by_pair = made.groupBy("word", "before").agg(F.sum("clean").alias("clean"))
    return by_pair.groupBy("word").agg(F.count("before").alias("toxic"), F.sum("clean").alias("clean"))


def _scored(sample: DataFrame, table: np.ndarray, bias: float) -> pd.DataFrame:
    """label, worst value and word of the bounded sample."""
    shipped = sample.sparkSession.sparkContext.broadcast(table.astype("f4"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shipped.value, bias)
        for batch in batches:
            found = scorer.worst([t or "" for t in batch.column(0).to_pylist()])
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array([v for v, _ in found], pa.float64()), pa.array([w for _, w in found], pa.string())], ["label", "value", "word"])

    return sample.mapInArrow(run, "label int, value double, word string").toPandas()


def _calibrated(value: np.ndarray, label: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the logistic curve through (value, label), both classes weighing alike."""
    x = np.stack([value, np.ones(len(value))], 1)
    share = np.where(label > 0, 0.5 / max(1, label.sum()), 0.5 / max(1, (1 - label).sum())) * len(label)
    w = np.array([4.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (share * (p - label)) + 1e-2 * w * len(label) / 100
        hess = (x * (share * p * (1 - p))[:, None]).T @ x + 1e-4 * len(label) * np.eye(2)
        w = w - np.linalg.solve(hess, grad)
    return float(max(w[0], 1e-3)), float(w[1])


def train(docs: DataFrame, labels: DataFrame, max_rows: int = 30_000, candidates: int = 800, others: int = 3_000) -> dict:
    """Fit on rows (doc_id, label) of labels joined with docs (doc_id, text). ``max_rows`` bounds the labelled
    rows used. ``candidates``, ``others`` and the landmarks bound the machine, whose kernels are solved on the driver:
    the words it starts from are those that set toxic sentences apart most, and as many ordinary ones by frequency and
    by chance; after each fit the worst words of clean sentences join them. What is scored is any word of any text.
    Null labels and ids are left out. Without both labels every score is the labels' mean."""
    labels = labels.filter("doc_id IS NOT NULL AND label IS NOT NULL").groupBy("doc_id").agg(F.max("label").cast("int").alias("label"))
    sample = _labelled(docs, labels, max_rows)
    counts = settle(_word_counts(sample), "words")
    suspects = {r["word"]: float(np.log1p(r["toxic"])) for r in counts.filter("toxic >= 2 AND toxic >= 8 * clean").orderBy(F.desc(F.col("toxic") - 4 * F.col("clean")), "word").limit(candidates).collect()}
    ordinary = counts.filter("clean > 0 AND toxic < 4 * clean")
    frequent = [r["word"] for r in ordinary.orderBy(F.desc("clean"), "word").limit(others).collect()]
    various = [r["word"] for r in ordinary.orderBy(F.xxhash64("word"), "word").limit(others).collect()]
    if not suspects or not frequent:
        mean = labels.agg(F.avg("label")).first()[0]
        return {"table": np.zeros(SLOTS), "bias": 0.0, "slope": 0.0, "offset": 0.0, "constant": float(mean or 0.0)}
    negative = list(dict.fromkeys(x for pair in zip(frequent, various, strict=False) for x in pair))
    return refine(suspects, negative, lambda table, bias: _scored(sample, table, bias), others)


def refine(suspects: dict[str, float], negative: list[str], look, others: int, turns: int = 2) -> dict:
    """Fit, look at the sample, and fit again: suspects on the wrong side go, being words that copies or
    chance brought into toxic texts, and the worst words of clean texts become negatives."""
    for turn in range(turns + 1):
        positive = sorted(suspects, key=lambda w: (-suspects[w], w))
        table, bias = fit_machine(positive, negative, np.array([suspects[w] for w in positive]))
        seen = look(table, bias)
        if turn == turns:
            break
        value = decisions(positive, table) + bias
        suspects = {w: suspects[w] for w, v in zip(positive, value, strict=True) if v > 0 or suspects[w] > np.log1p(SURE)} or suspects
        known = set(negative) | set(suspects)
        wrong = seen[(seen.label == 0) & (seen.value > -0.5)].groupby("word").value.max().sort_values(ascending=False)
        fresh = [w for w in wrong.index if w not in known][:others]
        negative = fresh[: len(fresh) // 2] + negative + fresh[len(fresh) // 2 :]
    slope, offset = _calibrated(seen.value.to_numpy(), seen.label.to_numpy())
    return {"table": table.astype("f4"), "bias": bias, "slope": slope, "offset": offset, "constant": None}


def score(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score (0 to 1) and worst_word of every row. Null and blank texts have no word and the least score."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        scorer = Scorer(m["table"], m["bias"])
        for batch in batches:
            values, words = [], []
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for i in range(0, len(texts), 500):
                for value, word in scorer.worst(texts[i : i + 500]):
                    values.append(m["constant"] if m["constant"] is not None else float(1 / (1 + np.exp(-np.clip(m["slope"] * value + m["offset"], -30, 30)))))
                    words.append(word)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values, pa.float64()), pa.array(words, pa.string())], ["doc_id", "score", "worst_word"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {docs.schema[id_col].dataType.simpleString()}, score double, worst_word string")


def keep_clean(docs: DataFrame, model: dict, limit: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, whose text scores below limit; null and blank texts stay."""
    shipped, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        scorer = Scorer(m["table"], m["bias"])
        for batch in batches:
            for i in range(0, batch.num_rows, 500):
                part = batch.slice(i, 500)
                values = np.array([v for v, _ in scorer.worst([t or "" for t in part.column(at).to_pylist()])])
                scores = np.full(len(values), m["constant"]) if m["constant"] is not None else 1 / (1 + np.exp(-np.clip(m["slope"] * values + m["offset"], -30, 30)))
                blank = np.array([not (t or "").strip() for t in part.column(at).to_pylist()])
                yield part.filter(pa.array(blank | (scores < limit)))

    return docs.mapInArrow(run, docs.schema)
