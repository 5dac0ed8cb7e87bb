"""Quality by a generalised additive model with pairwise interactions.

Features of a text are binned at quantiles; cyclic boosting visits one feature at a time and adds a shallow
tree over its bins to that feature's lookup table, then does the same over the pairs that explain most of
what is left. A score is a sum of table entries.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NAMES = ("words", "word_length", "upper", "digits", "symbols", "pipes", "marks", "function_words", "distinct", "repeats", "same_lines", "line_words", "beyond_ascii", "closed_words")

# Common function words of English, German, French and Spanish.
FUNCTION_WORDS = frozenset(
    "the of and to in a is that it for on was be with as by this at are an from or not have der die das und den von zu mit des ein eine nicht sich auf für ist im dem "
    "le la les et en un une du que est pour dans par sur avec au il elle qui ne el los las y se del una por con su para como".split()
)
_STOP = frozenset(w.encode() for w in FUNCTION_WORDS)
_CLASS = np.zeros((256, 6))
for _b in range(256):
    _c = chr(_b)
    _CLASS[_b] = [65 <= _b <= 90, 48 <= _b <= 57, _b < 128 and not _c.isalnum() and not _c.isspace() and _c not in ".,;:'\"()-", _c == "|", _c in "!?", _b >= 128]


def features(text: bytes) -> list[float]:
    """The values named in NAMES; all 0 for an empty text."""
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * len(NAMES)
    upper, digits, symbols, pipes, marks, beyond = (np.bincount(np.frombuffer(text, "u1"), minlength=256) @ _CLASS).tolist()
    low = [w.lower() for w in words]
    lines = [x for x in text.split(b"\n") if x.strip()]
    size = len(text)
    closed = sum(w[-1] in b".,;:!?" for w in words)
    return [
        float(np.log1p(n)), size / n - 1, upper / size, digits / size, symbols / size, pipes / size, marks / size,
        sum(w in _STOP for w in low) / n, len(set(low)) / n**0.8, sum(map(eq, low, low[1:])) / n, 1 - len(set(lines)) / len(lines),
        float(np.log1p(n / len(lines))), beyond / size, closed / n,
    ]


def feature_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and one double per name; a null text counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [features(t or b"") for t in batch.column(1).cast(pa.binary()).to_pylist()]
            columns = np.array(rows).reshape(-1, len(NAMES)).T
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c) for c in columns)], ["doc_id", *NAMES])

    made = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    return made.mapInArrow(run, f"doc_id {docs.schema[id_col].dataType.simpleString()}, " + ", ".join(f"{n} double" for n in NAMES))


def _shallow(grad: np.ndarray, hess: np.ndarray, depth: int, ridge: float) -> np.ndarray:
    """Leaf values over ordered bins of the tree that splits greedily to depth."""
    value = -grad.sum() / (hess.sum() + ridge)
    if depth == 0 or len(grad) < 2:
        return np.full(len(grad), value)
    g, h = np.cumsum(grad)[:-1], np.cumsum(hess)[:-1]
    gain = g**2 / (h + ridge) + (grad.sum() - g) ** 2 / (hess.sum() - h + ridge)
    gain[(h < 1) | (hess.sum() - h < 1)] = -1
    at = int(np.argmax(gain)) + 1
    if gain[at - 1] <= grad.sum() ** 2 / (hess.sum() + ridge) + 1e-9:
        return np.full(len(grad), value)
    return np.concatenate([_shallow(grad[:at], hess[:at], depth - 1, ridge), _shallow(grad[at:], hess[at:], depth - 1, ridge)])


def _quadrants(grad: np.ndarray, hess: np.ndarray, ridge: float) -> tuple[np.ndarray, float]:
    """Four leaves over a grid of bins, cut where they gain most; and that gain."""
    best, out = 0.0, np.zeros_like(grad)
    g, h = grad.cumsum(0).cumsum(1), hess.cumsum(0).cumsum(1)
    for i in range(1, grad.shape[0]):
        for j in range(1, grad.shape[1]):
            gs = np.array([g[i - 1, j - 1], g[i - 1, -1] - g[i - 1, j - 1], g[-1, j - 1] - g[i - 1, j - 1], 0.0])
            hs = np.array([h[i - 1, j - 1], h[i - 1, -1] - h[i - 1, j - 1], h[-1, j - 1] - h[i - 1, j - 1], 0.0])
            gs[3], hs[3] = g[-1, -1] - gs.sum(), h[-1, -1] - hs.sum()
            gain = float((gs**2 / (hs + ridge)).sum())
            if gain > best:
                best, v = gain, -gs / (hs + ridge)
                out = np.zeros_like(grad)
                out[:i, :j], out[:i, j:], out[i:, :j], out[i:, j:] = v
    return out, best


def fit(x: np.ndarray, y: np.ndarray, bins: int = 32, coarse: int = 8, rounds: int = 120, pair_rounds: int = 20, pairs: int = 6, rate: float = 0.15, depth: int = 2, ridge: float = 5.0) -> dict:
    """Lookup tables from rows x (n, len(NAMES)) and labels y (0 or 1)."""
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) if len(c) else np.empty(0) for c in x.T]
    wide = [np.unique(np.quantile(c, np.linspace(0, 1, coarse + 1)[1:-1])) if len(c) else np.empty(0) for c in x.T]
    base = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
    model = {"edges": edges, "wide": wide, "base": float(np.log(base / (1 - base))), "tables": [np.zeros(len(e) + 1) for e in edges], "pairs": {}}
    if len(set(y.tolist())) < 2:
        return model
    at = [np.searchsorted(e, c, "right") for e, c in zip(edges, x.T, strict=True)]
    at_wide = [np.searchsorted(e, c, "right") for e, c in zip(wide, x.T, strict=True)]
    raw = np.full(len(y), model["base"])

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-raw))
        return p - y, p * (1 - p)

    for _ in range(rounds):
        for f, table in enumerate(model["tables"]):
            g, h = slopes()
            step = rate * _shallow(np.bincount(at[f], g, len(table)), np.bincount(at[f], h, len(table)), depth, ridge)
            table += step
            raw = raw + step[at[f]]

    def grid(pair: tuple[int, int], g: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, b = pair
        shape = (len(wide[a]) + 1, len(wide[b]) + 1)
        cell = at_wide[a] * shape[1] + at_wide[b]
        return np.bincount(cell, g, shape[0] * shape[1]).reshape(shape), np.bincount(cell, h, shape[0] * shape[1]).reshape(shape)

    g, h = slopes()
    ranked = sorted(combinations(range(len(edges)), 2), key=lambda p: -_quadrants(*grid(p, g, h), ridge)[1])[:pairs]
    model["pairs"] = {p: np.zeros((len(wide[p[0]]) + 1, len(wide[p[1]]) + 1)) for p in ranked}
    for _ in range(pair_rounds):
        for (a, b), table in model["pairs"].items():
            step = rate * _quadrants(*grid((a, b), *slopes()), ridge)[0]
            table += step
            raw = raw + step[at_wide[a], at_wide[b]]
    return model


def predict(model: dict, x: np.ndarray) -> np.ndarray:
    raw = np.full(len(x), model["base"])
    for edges, table, c in zip(model["edges"], model["tables"], x.T, strict=True):
        raw += table[np.searchsorted(edges, c, "right")]
    for (a, b), table in model["pairs"].items():
        raw += table[np.searchsorted(model["wide"][a], x[:, a], "right"), np.searchsorted(model["wide"][b], x[:, b], "right")]
    return 1 / (1 + np.exp(-np.clip(raw, -30, 30)))


def train(table: DataFrame, labels: DataFrame, max_rows: int = 20_000) -> dict:
    """Fit on labels (doc_id, label) joined with a feature table. Where there are more than max_rows labels, those
    of least id hash are taken, about max_rows of them, and come to the driver. Null labels and ids are left out; an
    id counts once, with its greatest label and least row of features."""
    labels = labels.filter("doc_id IS NOT NULL AND label IS NOT NULL").groupBy("doc_id").agg(F.max("label").alias("label"))
    n = labels.count()
    if n > max_rows:
        labels = labels.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * max_rows / n))
    once = table.join(labels, "doc_id").groupBy("doc_id").agg(F.min(F.struct(*NAMES)).alias("x"), F.max("label").cast("double").alias("label"))
    sample = once.select("x.*", "label").toPandas()
    return fit(sample[list(NAMES)].to_numpy(), sample["label"].to_numpy())


def score(table: DataFrame, model: dict) -> DataFrame:
    """doc_id and score (0 to 1) of a feature table."""
    shipped = table.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.stack([batch.column(n).to_numpy(zero_copy_only=False) for n in NAMES], 1)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(predict(shipped.value, x))], ["doc_id", "score"])

    return table.mapInArrow(run, f"doc_id {table.schema['doc_id'].dataType.simpleString()}, score double")
