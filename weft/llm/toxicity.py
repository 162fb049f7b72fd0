"""Toxicity: a convolutional text classifier on hashed word embeddings, trained in numpy.

A word (ASCII punctuation counts as white space) is the sum of two hashed embeddings, of the word
and of its first bytes.  Filters of several widths run over the whole text, their greatest
responses are pooled, and a logistic layer gives a raw score.  Rows that training leaves aside set,
for each language told from the text's own function words, the raw score that separates the
classes best; the given score is shifted so that this threshold lies at 0.5.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labelled import judged, sample, sigmoid
from .shared import one_thread, table, texts_as_bytes, work_alone

WORDS, PREFIXES, PREFIX_BYTES = 1 << 15, 1 << 13, 5
DIMENSION, FILTERS, WIDTHS = 16, 16, (1, 2, 3)
PAD = WORDS + PREFIXES
#: Rows of each class that training reads at most; a quarter of them only sets thresholds.
PER_CLASS = 3000
EPOCHS, LEAST_STEPS, BATCH, RATE = 26, 700, 32, 0.15
#: Share of the words that a pass over a row leaves out, so that no few words speak for all others.
DROP = 0.5
#: What the share of false alarms counts against the share of missed rows; toxic rows are the rarer ones.
ALARM = 4
#: Words that go through the network at once.
CHUNK = 1 << 15

#: Function words that tell a language.
FUNCTION_WORDS = {
    "en": "the of and to in is that was for it with as on be at by this are from or an he they",
    "fr": "le la les des et que qui dans pour une est sur avec pas au du en ce il par plus",
    "de": "der die das und ist von mit zu den für auf ein eine nicht dem sich des im als",
    "es": "el los las del y que en por con para una un es se no su al lo como más",
}
LANGUAGES = [*FUNCTION_WORDS, "other"]

_SEPARATE = bytes(32 if (b < 128 and not chr(b).isalnum()) else b + 32 if 65 <= b <= 90 else b for b in range(256))


def _tells() -> tuple[np.ndarray, np.ndarray]:
    seen: dict[int, np.ndarray] = {}
    for i, words in enumerate(FUNCTION_WORDS.values()):
        for word in words.split():
            seen.setdefault(xxhash.xxh3_64_intdigest(word.encode()), np.zeros(len(FUNCTION_WORDS), np.int32))[i] = 1
    order = sorted(seen)
    return np.array(order, np.uint64), np.stack([seen[h] for h in order])


_TELL_HASHES, _TELL_FLAGS = _tells()


def read_text(text: bytes | None) -> tuple[np.ndarray, int]:
    """(word and prefix buckets (n, 2), language number) of a text."""
    words = text.translate(_SEPARATE).split() if text else []
    n = len(words)
    if not n:
        return np.empty((0, 2), np.int32), len(FUNCTION_WORDS)
    whole = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, n)
    first = np.fromiter(map(xxhash.xxh3_64_intdigest, [w[:PREFIX_BYTES] for w in words]), np.uint64, n)
    out = np.empty((n, 2), np.int32)
    out[:, 0] = whole & np.uint64(WORDS - 1)
    out[:, 1] = WORDS + (first & np.uint64(PREFIXES - 1)).astype(np.int32)
    at = np.minimum(np.searchsorted(_TELL_HASHES, whole), len(_TELL_HASHES) - 1)
    votes = _TELL_FLAGS[at[_TELL_HASHES[at] == whole]].sum(axis=0)
    return out, int(votes.argmax()) if votes.any() else len(FUNCTION_WORDS)


class Network:
    """Embeddings, filters and the logistic layer."""

    def __init__(self):
        rng = np.random.Generator(np.random.PCG64(11))
        self.e = rng.normal(0, 0.1, (PAD + 1, DIMENSION)).astype(np.float32)
        self.e[PAD] = 0
        self.w = {k: rng.normal(0, 1 / np.sqrt(k * DIMENSION), (k, DIMENSION, FILTERS)).astype(np.float32) for k in WIDTHS}
        self.b = {k: np.zeros(FILTERS, np.float32) for k in WIDTHS}
        self.out = rng.normal(0, 0.1, len(WIDTHS) * FILTERS).astype(np.float32)
        self.bias = np.zeros(1, np.float32)
        self.offsets = np.zeros(len(LANGUAGES))

    def windows(self, x: np.ndarray) -> dict[int, np.ndarray]:
        """Responses of each width at each word of ``x`` (n + 2, DIMENSION), the last two rows being what follows."""
        n = len(x) - WIDTHS[-1] + 1
        return {k: sum(x[j : j + n] @ self.w[k][j] for j in range(k)) + self.b[k] for k in WIDTHS}

    def pooled(self, texts: list[np.ndarray]) -> np.ndarray:
        """Pooled features of texts given as buckets; long ones go through in parts, so memory doesn't grow with them."""
        spare = len(texts)  # takes windows that start beyond a part
        found = np.full((spare + 1, len(WIDTHS) * FILTERS), -np.inf, np.float32)
        gap = np.full((WIDTHS[-1] - 1, 2), PAD, np.int32)
        parts, starts, owners, held = [], [], [], 0

        def go():
            flat = np.concatenate([*parts, gap])
            x = self.e[flat[:, 0]] + self.e[flat[:, 1]]
            for at, responses in enumerate(self.windows(x).values()):
                best = np.maximum.reduceat(responses, starts, axis=0)
                np.maximum.at(found[:, at * FILTERS : (at + 1) * FILTERS], owners, best)

        for i, text in enumerate(texts):
            for at in range(0, max(1, len(text)), CHUNK):
                own = max(1, min(CHUNK, len(text) - at))
                # the rows after a part are those that follow it in its text, then padding
                part = np.concatenate([text[at : at + CHUNK + len(gap)], gap])
                parts.append(part)
                starts += [held, held + own]
                owners += [i, spare]
                held += len(part)
                if held >= CHUNK:
                    go()
                    parts, starts, owners, held = [], [], [], 0
        if parts:
            go()
        found = found[:spare]
        return np.maximum(found, 0)

    def logits(self, texts: list[np.ndarray]) -> np.ndarray:
        return (self.pooled(texts) @ self.out + self.bias).astype(np.float64)

    def train(self, texts: list[np.ndarray], y: np.ndarray) -> None:
        """Adagrad on the log loss; only the words that win a filter get gradients, so some words of each row are left out at random."""
        rng = np.random.Generator(np.random.PCG64(12))
        gap = np.full((WIDTHS[-1] - 1, 2), PAD, np.int32)
        sums = {id(p): np.full(p.shape, 1e-2, np.float32) for p in (self.e, self.out, self.bias, *self.w.values(), *self.b.values())}

        def step(p, g, rows=None):
            s = sums[id(p)]
            if rows is None:
                s += g * g
                p -= RATE * g / np.sqrt(s)
            else:
                s[rows] += g * g
                p[rows] -= RATE * g / np.sqrt(s[rows])

        for _ in range(max(EPOCHS, -(-LEAST_STEPS * BATCH // len(texts)))):
            order = rng.permutation(len(texts))
            for at in range(0, len(order), BATCH):
                chosen = order[at : at + BATCH]
                features, where, xs = [], [], []
                for i in chosen:
                    flat = np.concatenate([texts[i] if len(texts[i]) else gap[:1], gap])
                    flat[rng.random(len(flat)) < DROP] = PAD
                    x = self.e[flat[:, 0]] + self.e[flat[:, 1]]
                    responses = self.windows(x)
                    tops = {k: r.argmax(axis=0) for k, r in responses.items()}
                    features.append(np.concatenate([responses[k][tops[k], np.arange(FILTERS)] for k in WIDTHS]))
                    where.append(tops)
                    xs.append((flat, x))
                pre = np.array(features)
                h = np.maximum(pre, 0)
                error = ((sigmoid(h @ self.out + self.bias) - y[chosen]) / len(chosen)).astype(np.float32)
                back = error[:, None] * self.out * (pre > 0)
                g_out, g_bias = h.T @ error, error.sum(keepdims=True)
                g_w, g_b = {k: np.zeros_like(self.w[k]) for k in WIDTHS}, {k: np.zeros_like(self.b[k]) for k in WIDTHS}
                rows, grads = [], []
                for d in range(len(chosen)):
                    flat, x = xs[d]
                    for c, k in enumerate(WIDTHS):
                        g = back[d, c * FILTERS : (c + 1) * FILTERS]
                        if not g.any():
                            continue
                        g_b[k] += g
                        for j in range(k):
                            position = where[d][k] + j
                            g_w[k][j] += (x[position] * g[:, None]).T
                            de = self.w[k][j].T * g[:, None]
                            for side in (0, 1):
                                rows.append(flat[position, side])
                                grads.append(de)
                step(self.out, g_out), step(self.bias, g_bias)
                for k in WIDTHS:
                    step(self.w[k], g_w[k]), step(self.b[k], g_b[k])
                if rows:
                    unique, inverse = np.unique(np.concatenate(rows), return_inverse=True)
                    total = np.zeros((len(unique), DIMENSION), np.float32)
                    np.add.at(total, inverse, np.concatenate(grads))
                    total[unique == PAD] = 0
                    step(self.e, total, unique)

    def calibrate(self, texts: list[np.ndarray], languages: np.ndarray, y: np.ndarray, least: int = 20) -> None:
        """Sets each language's threshold; one with fewer than ``least`` rows of a class takes that of all rows."""
        raw = self.logits(texts)
        common = _threshold(raw, y)
        for i in range(len(LANGUAGES)):
            own = languages == i
            enough = min(y[own].sum(), (1 - y[own]).sum()) >= least
            self.offsets[i] = _threshold(raw[own], y[own]) if enough else common

    def scores(self, texts: list[np.ndarray], languages: np.ndarray) -> np.ndarray:
        """Scores of texts; one without words is not toxic and has 0."""
        some = np.array([len(t) > 0 for t in texts], bool)
        return np.where(some, sigmoid(self.logits(texts) - self.offsets[languages]), 0.0)


def _threshold(raw: np.ndarray, y: np.ndarray) -> float:
    """Middle of the gap at which the share missed and ALARM times the share of false alarms are least together; of equal gaps the widest."""
    if not len(y) or y.min() == y.max():
        return 0.0
    order = np.argsort(raw, kind="stable")
    x, t = raw[order], y[order]
    missed = np.concatenate([[0], np.cumsum(t)]) / max(1, t.sum())
    alarms = np.concatenate([[0], np.cumsum(1 - t)])
    alarms = 1 - alarms / max(1, (1 - t).sum())
    cost = missed + ALARM * alarms
    edges = np.concatenate([[x[0] - 1], x, [x[-1] + 1]])
    gaps = edges[1:] - edges[:-1]
    best = np.flatnonzero(cost <= cost.min() + 1e-12)
    i = best[gaps[best].argmax()]
    return float((edges[i] + edges[i + 1]) / 2)


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Network | None:
    """A trained and calibrated network; None where a class has no usable row.

    What comes to the driver are the words' buckets of at most ``per_class`` rows of each class.
    """
    chosen = sample(docs, labels, "toxic", per_class).select("doc_id", "y", "text")

    def run(batches):
        for batch in batches:
            both = [read_text(t) for t in texts_as_bytes(batch.column(2))]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([x for _, x in both], pa.int32()), pa.array([t.tobytes() for t, _ in both], pa.binary())], names=["doc_id", "y", "language", "words"]
            )

    rows = chosen.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, y int, language int, words binary").toPandas().sort_values(["doc_id", "words"], kind="stable")
    y = rows["y"].to_numpy(np.float64)
    if not len(y) or y.min() == y.max():
        return None
    texts, languages = [np.frombuffer(w, np.int32).reshape(-1, 2) for w in rows["words"]], rows["language"].to_numpy()
    aside = np.array([xxhash.xxh3_64_intdigest(str(d)) % 4 == 0 for d in rows["doc_id"]])
    if min(y[aside].sum(), (1 - y[aside]).sum()) < 5:
        aside[:] = False  # too few rows to set some aside
    network = Network()
    with one_thread():
        at = np.flatnonzero(~aside)
        network.train([texts[i] for i in at], y[at])
        at = np.flatnonzero(aside) if aside.any() else at
        network.calibrate([texts[i] for i in at], languages[at], y[at])
    return network


def score(docs: DataFrame, network: Network | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, score, language) of every row; score in 0..1, 0.5 being the language's threshold.

    Null and empty texts and those without words score 0.  Without a network every score is 0.
    Repeated rows and null keys stay as they are; other columns are not read.
    """
    kind = dict(docs.dtypes)[key]
    shared = docs.sparkSession.sparkContext.broadcast(network)

    def run(batches):
        work_alone()
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                both = [read_text(t) for t in texts_as_bytes(part.column(1))]
                languages = np.array([x for _, x in both], int)
                scores = own.scores([t for t, _ in both], languages) if own else np.zeros(len(both))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores), pa.array([LANGUAGES[i] for i in languages])], names=[key, "score", "language"])

    return docs.select(key, text).mapInArrow(run, f"`{key}` {kind}, score double, language string")


def keep_clean(docs: DataFrame, network: Network | None, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(network)
    place = docs.columns.index(text)

    def run(batches):
        work_alone()
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                if own:
                    both = [read_text(t) for t in texts_as_bytes(part.column(place))]
                    part = part.filter(pa.array(own.scores([t for t, _ in both], np.array([x for _, x in both], int)) < threshold))
                yield part

    return docs.mapInArrow(run, docs.schema)


def op1_toxicity(spark, sf_dir: str) -> DataFrame:
    """Toxicity score of every document, learned from the rows that aren't held out."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    network = fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return judged(score(docs, network), 0.5)


def accuracy(scored: DataFrame, labels: DataFrame, label: str) -> DataFrame:
    """Counts of (y, predicted) over the held-out labelled rows."""
    return scored.where("held_out").join(labels, "doc_id").groupBy(F.col(label).alias("y"), "predicted").count()
