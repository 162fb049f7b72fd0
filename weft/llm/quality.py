"""Quality classifier: a generalised additive model with pairwise interactions.

Each feature of a text is cut into bins.  Boosting goes round the features: every turn fits a
shallow tree to the current gradients of one feature's bins and adds it to that feature's lookup
table.  Then the pairs of features whose joint bins explain most of what is left get tables of
their own, boosted in the same way.  A score is the sum of the tables' entries at the text's bins.
"""

from __future__ import annotations

from collections import Counter
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .labelled import judged, sample, sigmoid, usable_labels
from .shared import LOWER, table, texts_as_bytes

FEATURES = (
    "log_words", "bytes_per_word", "upper_share", "bang_share", "mark_share", "digit_share", "other_byte_share", "distinct_words",
    "repeats_in_a_row", "commonest_word", "words_per_line", "distinct_lines", "short_words", "longest_word", "control_share", "symbol_share",
)
#: Rows of each class that training reads at most.
PER_CLASS = 10_000
BINS, PAIR_BINS, PAIRS, ROUNDS, PAIR_ROUNDS, RATE, LEAST = 32, 8, 6, 120, 60, 0.15, 5


def _classes() -> np.ndarray:
    """Byte classes, as rows of 0 and 1: upper, bang, mark, digit, beyond ASCII, control, symbol."""
    rows = np.zeros((7, 256))
    for b in range(256):
        c = chr(b)
        rows[0, b] = "A" <= c <= "Z"
        rows[1, b] = c == "!"
        rows[2, b] = c in ".,;:?'\"()-"
        rows[3, b] = "0" <= c <= "9"
        rows[4, b] = b >= 128
        rows[5, b] = b < 32 and c not in "\n"
        rows[6, b] = c in "#$%&*+/<=>@[\\]^_`{|}~"
    return rows.T.copy()


_CLASSES = _classes()


def features(text: bytes | None) -> list[float]:
    """Features of a text; null and empty texts have zeros."""
    if not text:
        return [0.0] * len(FEATURES)
    upper, bang, mark, digit, other, control, symbol = np.bincount(np.frombuffer(text, np.uint8), minlength=256) @ _CLASSES
    size = len(text)
    words = text.translate(LOWER).split()
    n = len(words)
    if not n:
        return [0.0, 0.0, 0.0, bang / size, mark / size, 0.0, other / size, 0.0, 0.0, 0.0, 0.0, 0.0, 0.0, 0.0, control / size, symbol / size]
    counts = Counter(words)
    lines = [x for x in text.split(b"\n") if x.strip()]
    lengths = [*map(len, words)]
    return [
        np.log1p(n), size / n, upper / size, bang / size, mark / size, digit / size, other / size, len(counts) / n,
        sum(map(eq, words, words[1:])) / n, max(counts.values()) / n, n / max(1, len(lines)), len(set(lines)) / max(1, len(lines)),
        sum(x <= 3 for x in lengths) / n, float(max(lengths)), control / size, symbol / size,
    ]


def _tree(g: np.ndarray, h: np.ndarray, depth: int = 2) -> np.ndarray:
    """Values of a shallow tree over ordered bins, fitted to sums of gradients and hessians."""
    value = np.full(len(g), g.sum() / (h.sum() + 1.0))
    if depth == 0 or len(g) < 2:
        return value
    gl, hl = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    gr, hr = g.sum() - gl, h.sum() - hl
    gain = gl**2 / (hl + 1.0) + gr**2 / (hr + 1.0)
    gain[(hl < LEAST * 0.05) | (hr < LEAST * 0.05)] = -np.inf
    at = int(gain.argmax())
    if not np.isfinite(gain[at]) or gain[at] <= g.sum() ** 2 / (h.sum() + 1.0) + 1e-9:
        return value
    return np.concatenate([_tree(g[: at + 1], h[: at + 1], depth - 1), _tree(g[at + 1 :], h[at + 1 :], depth - 1)])


def _plane(g: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, float]:
    """Values of the best tree that cuts both axes once, over a grid of sums; and its gain."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    tg, th = cg[-1, -1], ch[-1, -1]
    a_g, a_h = cg[:-1, :-1], ch[:-1, :-1]
    b_g, b_h = cg[:-1, -1:] - a_g, ch[:-1, -1:] - a_h
    c_g, c_h = cg[-1:, :-1] - a_g, ch[-1:, :-1] - a_h
    d_g, d_h = tg - a_g - b_g - c_g, th - a_h - b_h - c_h
    gain = sum(x**2 / (y + 1.0) for x, y in ((a_g, a_h), (b_g, b_h), (c_g, c_h), (d_g, d_h)))
    i, j = np.unravel_index(int(gain.argmax()), gain.shape)
    out = np.empty_like(g)
    for rows, columns, x, y in ((slice(0, i + 1), slice(0, j + 1), a_g, a_h), (slice(0, i + 1), slice(j + 1, None), b_g, b_h), (slice(i + 1, None), slice(0, j + 1), c_g, c_h), (slice(i + 1, None), slice(j + 1, None), d_g, d_h)):
        out[rows, columns] = x[i, j] / (y[i, j] + 1.0)
    return out, float(gain[i, j])


class Additive:
    """Lookup tables of single features and of pairs."""

    def __init__(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray):
        self.edges = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1])) for c in x.T]
        self.coarse = [np.unique(np.quantile(c, np.linspace(0, 1, PAIR_BINS + 1)[1:-1])) for c in x.T]
        share = np.clip((weight * y).sum() / weight.sum(), 1e-6, 1 - 1e-6)
        self.base = float(np.log(share / (1 - share)))
        self.tables = [np.zeros(len(e) + 1) for e in self.edges]
        self.pairs: list[tuple[int, int, np.ndarray]] = []
        bins, coarse = self._bins(x, self.edges), self._bins(x, self.coarse)
        total = np.full(len(y), self.base)
        for _ in range(ROUNDS):
            for f in range(x.shape[1]):
                g, h = self._sums(total, y, weight, bins[:, f], len(self.tables[f]))
                step = RATE * _tree(g, h)
                self.tables[f] += step
                total += step[bins[:, f]]
        found = []
        for a in range(x.shape[1]):
            for b in range(a + 1, x.shape[1]):
                shape = (len(self.coarse[a]) + 1, len(self.coarse[b]) + 1)
                if min(shape) > 1:
                    g, h = self._sums(total, y, weight, coarse[:, a] * shape[1] + coarse[:, b], shape[0] * shape[1])
                    found.append((_plane(g.reshape(shape), h.reshape(shape))[1], -a, -b, shape))
        for _, a, b, shape in sorted(found, reverse=True)[:PAIRS]:
            self.pairs.append((-a, -b, np.zeros(shape)))
        for _ in range(PAIR_ROUNDS):
            for a, b, values in self.pairs:
                cell = coarse[:, a] * values.shape[1] + coarse[:, b]
                g, h = self._sums(total, y, weight, cell, values.size)
                step = RATE * _plane(g.reshape(values.shape), h.reshape(values.shape))[0]
                values += step
                total += step.ravel()[cell]

    @staticmethod
    def _bins(x, edges):
        return np.stack([np.searchsorted(e, c, side="right") for e, c in zip(edges, x.T)], axis=1)

    @staticmethod
    def _sums(total, y, weight, cell, size):
        p = sigmoid(total)
        return np.bincount(cell, weight * (y - p), size), np.bincount(cell, weight * p * (1 - p), size)

    def scores(self, x: np.ndarray) -> np.ndarray:
        bins, coarse = self._bins(x, self.edges), self._bins(x, self.coarse)
        total = np.full(len(x), self.base)
        for f, values in enumerate(self.tables):
            total += values[bins[:, f]]
        for a, b, values in self.pairs:
            total += values[coarse[:, a], coarse[:, b]]
        return sigmoid(total)


def described(docs: DataFrame, *others: str) -> DataFrame:
    """(others, features array<double>) of every row of (others, text)."""
    kinds = dict(docs.dtypes)

    def run(batches):
        for batch in batches:
            rows = [features(t) for t in texts_as_bytes(batch.column(len(others)))]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(others))), pa.array(rows, pa.list_(pa.float64()))], names=[*others, "features"])

    return docs.select(*others, "text").mapInArrow(run, ", ".join(f"`{c}` {kinds[c]}" for c in others) + ", features array<double>")


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Additive | None:
    """A trained model; None where a class has no usable row.

    Only features come to the driver.  Rows are weighted so that the classes have the shares that
    they have among all usable labels.
    """
    rows = described(sample(docs, labels, "quality", per_class), "doc_id", "y").toPandas().sort_values("doc_id", kind="stable")
    y = rows["y"].to_numpy(np.float64)
    if not len(y) or y.min() == y.max():
        return None
    among = {r.y: r["count"] for r in usable_labels(labels, "quality").groupBy("y").count().collect()}  # two rows
    weight = np.where(y == 1, among[1] / y.sum(), among[0] / (1 - y).sum())
    return Additive(np.stack(rows["features"].to_list()), y, weight / weight.mean())


def score(docs: DataFrame, model: Additive | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, score) of every row, score in 0..1.

    Null and empty texts have zeros as features.  Without a model every score is 0.  Repeated rows
    and null keys stay as they are; other columns are not read.
    """
    kind = dict(docs.dtypes)[key]
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        own = shared.value
        for batch in batches:
            if batch.num_rows:
                x = np.array([features(t) for t in texts_as_bytes(batch.column(1))])
                scores = own.scores(x) if own else np.zeros(len(x))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores)], names=[key, "score"])

    return docs.select(key, text).mapInArrow(run, f"`{key}` {kind}, score double")


def op5_quality(spark, sf_dir: str) -> DataFrame:
    """Quality score of every document, learned from the rows that aren't held out."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return judged(score(docs, fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))), 0.3)
