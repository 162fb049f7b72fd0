"""Language-model scoring: causal self-attention on subword ids, beside a smoothed word-count score.

The model reads the subword ids of a text's words and an end id.  A text is cut into blocks; each
window is two blocks, of which the second is scored and the first is context, so windows overlap
and every id is scored once.  One masked attention layer with relative position biases and one
feed-forward layer give a vector for each position, from which the next id follows by a binary
code tree: a logistic choice at each node, frequent ids having short codes.  The odds of all nodes
come from the counts of all training documents; the upper nodes also look at the vector, the deep
ones, which tell rare ids apart, keep their odds.  The score of a text is the sum over its ids, so
the probabilities of all texts sum to 1 at most.

Weights are trained in numpy inside tasks, on every id of every training document.  Documents are
dealt to rounds and parts by a hash and cut into windows in the task that learns from them, so windows
are neither written nor exchanged.  Each part of a round starts from the same weights, and what the
parts learned is averaged, each row of a weight by how often a part used it.  Only weights come to the
driver.

The base score needs the corpus count of every word of every text.  The commonest words' counts
are part of what scoring tasks get; the others are listed with their documents, meet the corpus
counts in a join on the word, and sums go back to the documents.  Neither texts nor a vocabulary
are sent around whole, and no word of the join is a hot key.
"""

from __future__ import annotations

import base64
import heapq
import math
from collections import Counter
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
import tiktoken
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .pieces import PIECE_PATTERN, read_vocabulary
from .shared import Workspace, held_out, mix, table, texts_as_bytes, words_of, work_alone

FOLDS, HELD_OUT = 7, 2
#: Ids of one block; a window is two blocks.
BLOCK = 8
SPAN = 2 * BLOCK + 1  # ids that a window's inputs and targets come from
DIMENSION, HIDDEN = 16, 16
#: Levels of the code tree whose choices depend on the context.
DEPTH = 8
#: Choices that ids of one group share; steps of training whose places are worked out at once.
SPLIT, STRETCH = 3, 32
#: Words of a run, and one run in so many that gives windows to train on: all of them.
RUN, SHARE = 64, 1
#: Rounds of training, windows of one part of a round, windows of a step, and the rate of a step.
ROUNDS, PART, BATCH, RATE = 4, 1 << 18, 64, 0.1
#: Bytes of texts or windows whose windows are trained on in one random order.
MIXED = 1 << 22
#: Words whose counts are sent to every task, at most; the others' counts come by a join.
COMMON = 100_000
#: Distinct words that one run counts, and distinct words that a worker keeps the ids of.
RUN_WORDS, KEPT_WORDS = 300_000, 400_000
#: Ids that go through the model at once.
CHUNK = 1 << 12
_END = b""  # no word is empty


class Ids:
    """Subword ids of words and the counts of common ones, kept for the words met lately."""

    def __init__(self, source: str, common: dict[bytes, int] | None = None):
        self.common = common or {}
        ranks = {base64.b64decode(a): int(b) for a, b in map(str.split, source.splitlines())}
        self.coder = tiktoken.Encoding("ids", pat_str=PIECE_PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.end = max(ranks.values()) + 1  # the id that no text has
        self.reset()

    def reset(self) -> None:
        self.place: dict[bytes, int] = {}
        self.flat, self.used, self.known = np.empty(1 << 16, np.int32), 0, 0
        self.starts, self.lengths, self.counts = (np.empty(1 << 14, np.int64) for _ in range(3))

    def _room(self, ids: int, words: int) -> None:
        while self.used + ids > len(self.flat):
            self.flat = np.concatenate([self.flat, np.empty_like(self.flat)])
        while self.known + words > len(self.starts):
            self.starts, self.lengths, self.counts = (np.concatenate([x, np.empty_like(x)]) for x in (self.starts, self.lengths, self.counts))

    def learn(self, words: list[bytes]) -> None:
        """Learn new words, distinct ones."""
        place, new = self.place, words
        encode = self.coder.encode_ordinary
        for at in range(0, len(new), 20_000):
            part = new[at : at + 20_000]
            found = [encode(" " + w.decode()) for w in part]
            lengths = np.fromiter(map(len, found), np.int64, len(found))
            total, n = int(lengths.sum()), len(part)
            self._room(total, n)
            own = slice(self.known, self.known + n)
            self.flat[self.used : self.used + total] = np.fromiter(chain.from_iterable(found), np.int32, total)
            self.starts[own], self.lengths[own] = self.used + np.cumsum(lengths) - lengths, lengths
            self.counts[own] = [self.common.get(w, 0) for w in part] if self.common else 0
            place.update(zip(part, range(self.known, self.known + n)))
            self.used += total
            self.known += n

    def of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids of all words one after another, number of ids of each word, count of each word or 0)."""
        at = np.fromiter(map(self.place.get, words, repeat(-1)), np.int64, len(words))
        gaps = np.flatnonzero(at < 0).tolist()
        if gaps:
            new = list({words[i] for i in gaps})
            if self.known + len(new) > KEPT_WORDS and self.known:
                self.reset()
                self.learn(list(set(words)))
                at = np.fromiter(map(self.place.__getitem__, words), np.int64, len(words))
            else:
                self.learn(new)
                at[gaps] = [self.place[words[i]] for i in gaps]
        lengths = self.lengths[at]
        shift = np.repeat(self.starts[at] - np.cumsum(lengths) + lengths, lengths)
        return self.flat[shift + np.arange(len(shift))], lengths, self.counts[at]

    def texts(self, lists: list[list[bytes]]) -> tuple[list[np.ndarray], np.ndarray]:
        """Of texts given as words: (ids of each with the end id, count of every word)."""
        ids, lengths, counts = self.of([w for words in lists for w in words])
        borders = np.cumsum(np.array([*map(len, lists)], np.int64))
        edges = np.concatenate([[0], np.cumsum(lengths)])[np.concatenate([[0], borders])]
        return [np.append(ids[a:b], self.end).astype(np.int32) for a, b in zip(edges[:-1], edges[1:])], counts


_IDS: dict = {}


def _ids(source, common: dict | None = None) -> Ids:
    key = (hash(source.value), id(common))
    if key not in _IDS:
        _IDS.clear()
        _IDS[key] = Ids(source.value, common)
    return _IDS[key]


def code_tree(counts: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Binary code tree of ids by their counts plus one, cut at ``depth``.

    Returns for each id the numbers of its upper nodes and the signs of its choices there (+1 left, -1
    right), the log10 probability of its choices below by the counts alone, and the log odds of left
    of the numbered nodes.  Codes shorter than ``depth`` are filled up with the last node, whose odds
    make left certain.
    """
    n = len(counts)
    weight = [int(c) + 1 for c in counts]
    heap = [(w, i) for i, w in enumerate(weight)]
    heapq.heapify(heap)
    children: list[tuple[int, int]] = []
    while len(heap) > 1:
        (wa, a), (wb, b) = heapq.heappop(heap), heapq.heappop(heap)
        children.append((a, b))
        weight.append(wa + wb)
        heapq.heappush(heap, (wa + wb, n + len(children) - 1))
    nodes, signs = np.full((n, depth), -1, np.int64), np.ones((n, depth), np.float32)
    deep, bias = np.zeros(n), []
    stack = [(heap[0][1], (), ())] if heap else []
    while stack:
        node, way, sign = stack.pop()
        if node < n:
            nodes[node, : len(way)], signs[node, : len(way)] = way, sign
        elif len(way) < depth:
            a, b = children[node - n]
            bias.append(math.log(weight[a] / weight[b]))
            stack += [(a, (*way, len(bias) - 1), (*sign, 1)), (b, (*way, len(bias) - 1), (*sign, -1))]
        else:
            below = [node]  # ids under a node of the last level share its way
            while below:
                inner = below.pop()
                if inner < n:
                    nodes[inner], signs[inner] = way, sign
                    deep[inner] = math.log10(weight[inner] / weight[node])
                else:
                    below += children[inner - n]
    nodes[nodes < 0] = len(bias)
    return nodes, signs, deep, np.array([*bias, 30], np.float32)


def _limit(a: np.ndarray, low: float, high: float) -> None:
    """Clip in place; against arrays, with which numpy is some four times faster than with numbers."""
    flat = a.reshape(-1, a.shape[-1] * (a.shape[-2] if a.ndim > 2 else 1))
    np.maximum(flat, np.full(flat.shape[1], low, np.float32), out=flat)
    np.minimum(flat, np.full(flat.shape[1], high, np.float32), out=flat)


class Tree:
    """Where the upper nodes of a code tree stand among those of their group.

    A group is what codes share that start with the same ``SPLIT`` choices.  Ids dealt by groups need
    the products of their vectors with the nodes of their group alone, some tenth of all nodes.
    """

    def __init__(self, nodes: np.ndarray, signs: np.ndarray, last: int):
        heads = (nodes * 2 + (signs > 0))[:, :SPLIT]
        _, group = np.unique(heads, axis=0, return_inverse=True)
        self.group = group.ravel().astype(np.uint8)
        own = [np.unique(nodes[self.group == g]) for g in range(int(self.group.max()) + 1)]
        own = [held[held < last] for held in own]
        self.width = max(map(len, own)) + 1  # the last column stands for the node that fills up
        self.columns = np.full((len(own), self.width), last)
        self.place = np.full(nodes.shape, self.width - 1)
        for g, held in enumerate(own):
            self.columns[g, : len(held)] = held
            ids = np.flatnonzero(self.group == g)
            if len(held):
                at = np.searchsorted(held, nodes[ids])
                self.place[ids] = np.where(nodes[ids] < last, at, self.width - 1)
        self.place = self.place.astype(np.int16)
        flat = self.columns.ravel()
        self.first = np.array([np.flatnonzero(flat == node)[0] for node in range(last)], np.int64)
        shared = np.flatnonzero(np.bincount(flat, minlength=last + 1)[:last] > 1)
        self.shared, self.whole = shared, (flat == shared[:, None]).astype(np.float32)

    def deal(self, y: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of ids in rows: (places in the order of groups, borders of the groups, ids in that order, their codes' places in products)."""
        group = self.group.take(y)
        order = np.argsort(group, axis=1, kind="stable")
        borders = np.zeros((len(y), len(self.columns) + 1), np.int64)
        step = np.arange(len(y))[:, None] * len(self.columns)
        borders[:, 1:] = np.bincount((group + step).ravel(), minlength=step.size * len(self.columns)).reshape(len(y), -1)
        dealt = y.ravel().take(order + np.arange(0, y.size, y.shape[1])[:, None])
        at = self.place.take(dealt, axis=0) + (np.arange(y.shape[1]) * self.width)[:, None]
        return order, borders.cumsum(axis=1), dealt, at


class Model:
    """Weights, and the forward and backward passes."""

    def __init__(self, counts: np.ndarray, end: int):
        rng = np.random.Generator(np.random.PCG64(21))
        self.end, size, d = end, len(counts), DIMENSION
        self.nodes, self.signs, self.deep, bias = code_tree(counts, DEPTH)
        self.tree = Tree(self.nodes, self.signs, len(bias) - 1)
        draw = lambda *shape: rng.normal(0, 1 / math.sqrt(d), shape).astype(np.float32)
        self.p = {
            "e": draw(size, d), "q": draw(d, d), "k": draw(d, d), "v": draw(d, d) * 0.5, "w1": draw(d, HIDDEN), "b1": np.zeros((1, HIDDEN), np.float32),
            "w2": draw(HIDDEN, d) * 0.5, "near": np.zeros((2 * BLOCK, 1), np.float32), "node": np.zeros((len(bias), d), np.float32), "bias": bias[:, None],
        }
        self.sums = {k: np.full(v.shape, 1e-3, np.float32) for k, v in self.p.items()}
        place = np.arange(BLOCK)[:, None] + BLOCK - np.arange(2 * BLOCK)[None, :]  # distance of a key before its query
        self.distance, self.future = np.clip(place, 0, 2 * BLOCK - 1), place < 0

    def _mask(self) -> np.ndarray:
        return np.where(self.future, -60.0, self.p["near"][self.distance, 0]).astype(np.float32)

    def ready(self) -> None:
        """Tables of what scoring looks up for each id: its embedding, query, key and value; the nodes of each group."""
        p = self.p
        self.table = np.concatenate([p["e"], p["e"] @ p["q"] / np.float32(math.sqrt(DIMENSION)), p["e"] @ p["k"], p["e"] @ p["v"]], axis=1)
        self.mask, self.against = self._mask(), -self.signs
        self.out = np.ascontiguousarray(np.concatenate([p["node"], p["bias"]], axis=1)[self.tree.columns].transpose(0, 2, 1))

    def log10(self, blocks: np.ndarray, targets: np.ndarray, alone: np.ndarray) -> np.ndarray:
        """log10 probability of each target id.

        ``blocks`` (n, BLOCK): input ids; each but the first is scored, the one before it being its
        context unless it stands ``alone``; ``targets`` (n - 1, BLOCK): ids that follow, -1 for none.
        """
        p, d, n, tree = self.p, DIMENSION, len(blocks) - 1, self.tree
        found = self.table.take(blocks.ravel(), axis=0)
        # every block with the one before, as a view: windows overlap and nothing is copied
        row, item = found.strides
        pairs = lambda part: np.lib.stride_tricks.as_strided(found[:, part * d :], (n, 2 * BLOCK, d), (BLOCK * row, row, item))
        own = found[BLOCK:].reshape(n, BLOCK, 4 * d)
        a = own[:, :, d : 2 * d] @ pairs(2).transpose(0, 2, 1)
        a += self.mask
        a[alone, :, :BLOCK] = -60.0
        _limit(a, -60, 30)
        np.exp(a, out=a)
        h = (a @ pairs(3)).reshape(-1, d)
        h /= a.reshape(-1, 2 * BLOCK) @ np.ones((2 * BLOCK, d), np.float32)  # each row's sum in every column
        h += found[BLOCK:, :d]
        u = h @ p["w1"]
        u += p["b1"]
        np.maximum(u, np.zeros_like(u), out=u)
        h += u @ p["w2"]
        y = targets.ravel()
        y = np.where(y >= 0, y, 0)
        order, borders, y, at = (x[0] for x in tree.deal(y[None]))
        z = np.ones((len(y), d + 1), np.float32)
        z[:, :d] = h.take(order, axis=0)
        odds = np.empty((len(y), tree.width), np.float32)
        for nodes, lo, hi in zip(self.out, borders[:-1].tolist(), borders[1:].tolist()):
            np.matmul(z[lo:hi], nodes, out=odds[lo:hi])
        s = odds.ravel().take(at)
        s *= self.against.take(y, axis=0)
        _limit(s, -25, 25)
        np.exp(s, out=s)
        s += 1
        product = s[:, 0].astype(np.float64)
        for i in range(1, DEPTH):
            product *= s[:, i]
        out = np.empty(len(y))
        out[order] = self.deep.take(y) - np.log10(product)
        return np.where(targets.ravel() >= 0, out, 0.0)

    def train(self, spans: np.ndarray, seed: int) -> dict[str, tuple[np.ndarray, np.ndarray]]:
        """Adagrad over windows (n, SPAN) in random order; returns for each weight the rows used and how often.

        A span is what a window's inputs and targets come from: -1 stands for what isn't there.
        """
        p, sums = self.p, self.sums
        lesson = Lesson(p, sums, self)
        used, steps = [np.empty(0, np.int64)], 0
        order = np.random.Generator(np.random.PCG64(seed)).permutation(len(spans))
        whole = len(order) // BATCH * BATCH
        for begin in [*range(0, whole, BATCH * STRETCH), *([whole] if whole < len(order) else [])]:
            end = min(begin + BATCH * STRETCH, whole) if begin < whole else len(order)
            part = spans[order[begin:end]].reshape(-1, BATCH if begin < whole else end - begin, SPAN)
            used.append(lesson.study(part, p["e"], sums["e"]))
            steps += len(part)
        lesson.give(p, sums)
        uses = np.bincount(np.concatenate(used), minlength=len(p["e"])).astype(float)
        told = {k: (np.arange(len(v) if steps else 0), np.full(len(v) if steps else 0, float(steps))) for k, v in p.items() if k != "e"}
        return {"e": (np.flatnonzero(uses), uses[uses > 0]), **told}


class Lesson:
    """Steps of training; all weights but the embeddings lie in one vector meanwhile."""

    def __init__(self, p: dict, sums: dict, model: Model):
        self.model, self.tree, d = model, model.tree, DIMENSION
        shapes = {"q": (d, d), "k": (d, d), "v": (d, d), "w1": (d, HIDDEN), "b1": (1, HIDDEN), "w2": (HIDDEN, d), "near": (2 * BLOCK, 1), "odds": (len(p["bias"]), d + 1)}
        ends = np.cumsum([math.prod(s) for s in shapes.values()]).tolist()
        self.vector, self.squares, self.slope = (np.zeros(ends[-1], np.float32) for _ in range(3))
        cut = lambda v: {k: v[e - math.prod(s) : e].reshape(s) for (k, s), e in zip(shapes.items(), ends)}
        self.p, self.sums, self.g = cut(self.vector), cut(self.squares), cut(self.slope)
        for own, given in ((self.p, p), (self.sums, sums)):
            for name, held in self._named(own).items():
                held[:] = given[name]
        self.distance, self.ahead = model.distance.ravel(), np.flatnonzero(model.future.ravel())
        # adds up slopes of one distance; what lies ahead has none
        self.by_distance = np.zeros((BLOCK * 2 * BLOCK, 2 * BLOCK), np.float32)
        past = np.flatnonzero(~model.future.ravel())
        self.by_distance[past, model.distance.ravel()[past]] = 1
        self.held = None

    @staticmethod
    def _named(own: dict) -> dict:
        d = DIMENSION
        return {**{k: own[k] for k in ("q", "k", "v", "w1", "b1", "w2", "near")}, "node": own["odds"][:, :d], "bias": own["odds"][:, d:]}

    def give(self, p: dict, sums: dict) -> None:
        """Put the weights back."""
        for own, to in ((self.p, p), (self.sums, sums)):
            for name, held in self._named(own).items():
                to[name][:] = held

    def study(self, spans: np.ndarray, e: np.ndarray, sums: np.ndarray) -> np.ndarray:
        """Take the steps (n, windows, SPAN) one after another, with the embeddings and their sums; returns each step's distinct ids."""
        model, tree = self.model, self.tree
        count, b = spans.shape[:2]
        x = np.where(spans[:, :, :-1] < 0, model.end, spans[:, :, :-1]).reshape(count, -1)
        y = spans[:, :, BLOCK + 1 :].reshape(count, -1)
        real = y >= 0
        y = np.where(real, y, 0)
        alone = spans[:, :, 0] < 0
        order, borders, dealt, at = tree.deal(y)
        back = np.empty_like(order)
        np.put_along_axis(back, order, np.arange(order.shape[1])[None], axis=1)
        signs = model.signs.take(dealt, axis=0)
        # loss: sum of log(1 + exp(-s)), averaged over ids
        share = (real / -np.maximum(1, real.sum(axis=1, keepdims=True))).astype(np.float32)
        push = signs * np.take_along_axis(share, order, axis=1)[:, :, None]
        # equal ids of a step side by side
        wide = x.shape[1]
        keys = x.astype(np.int64 if len(e) * wide >> 31 else np.int32)
        keys *= wide
        keys += np.arange(wide, dtype=keys.dtype)
        keys.sort(axis=1)
        found = keys // wide
        lead = np.ones(found.shape, bool)
        np.not_equal(found[:, 1:], found[:, :-1], out=lead[:, 1:])
        number = np.empty(found.shape, np.int64)  # of a place's id among the step's distinct ones
        np.put_along_axis(number, (keys - found * wide).astype(np.int64), np.cumsum(lead, axis=1) - 1, axis=1)
        distinct = np.split(found[lead].astype(np.int64), np.cumsum(lead.sum(axis=1))[:-1])
        row = np.dtype((np.void, e.itemsize * e.shape[1]))
        e_rows, sums_rows = e.view(row).ravel(), sums.view(row).ravel()  # whole rows are put faster
        for i, ids in enumerate(distinct):
            own = e.take(ids, axis=0)
            slopes = self.step(own, number[i], alone[i], order[i], back[i], borders[i].tolist(), at[i], signs[i], push[i], b)
            cells = (number[i][:, None] * DIMENSION + np.arange(DIMENSION)).ravel()
            total = np.bincount(cells, slopes.ravel(), len(ids) * DIMENSION).astype(np.float32).reshape(-1, DIMENSION)
            squares = sums.take(ids, axis=0)
            squares += total * total
            total *= RATE
            total /= np.sqrt(squares)
            own -= total
            sums_rows[ids], e_rows[ids] = squares.view(row).ravel(), own.view(row).ravel()
        return np.concatenate(distinct)

    def step(self, e, x, alone, order, back, borders, at, signs, push, b) -> np.ndarray:
        """One step of all weights but the embeddings; returns the slopes of the inputs ``x``, told as rows of ``e``."""
        p, g, tree, d, wide = self.p, self.g, self.tree, DIMENSION, 2 * BLOCK
        n = b * BLOCK
        scale = np.float32(1 / math.sqrt(d))
        if self.held is None or len(self.held[0]) != n:
            laid, full = np.zeros((n, tree.width), np.float32), lambda x, *shape: np.full(shape, x, np.float32)
            self.held = laid, np.empty_like(laid), full(1, n, d + 1), np.empty((n, d), np.float32), full(1, wide, wide), full(1, 1, n)
            # numpy compares arrays some four times faster than an array with a number
            self.limits = full(-60, b, BLOCK, wide), full(30, b, BLOCK, wide), full(0, n, HIDDEN), full(1, n, HIDDEN), full(30, n, DEPTH)
        laid, odds, z, dz, ones, every = self.held
        lowest, highest, none, one, most = self.limits
        # ids repeat within a step: products once for each, then looked up
        e2f, k, v = e.take(x, axis=0), (e @ p["k"]).take(x, axis=0).reshape(b, wide, d), (e @ p["v"]).take(x, axis=0).reshape(b, wide, d)
        later = x.reshape(b, wide)[:, BLOCK:].ravel()
        ef, q = e.take(later, axis=0), (e @ (p["q"] * scale)).take(later, axis=0).reshape(b, BLOCK, d)
        a = q @ k.transpose(0, 2, 1)
        mask = p["near"].ravel().take(self.distance)
        mask[self.ahead] = -60
        a.reshape(b, -1)[:] += mask
        a[alone, :, :BLOCK] = -60.0
        np.maximum(a, lowest, out=a)
        np.minimum(a, highest, out=a)
        np.exp(a, out=a)
        af = a.reshape(-1, wide)
        af /= af @ ones
        hf = (a @ v).reshape(-1, d)
        hf += ef
        u = hf @ p["w1"]
        u += p["b1"]
        r = np.maximum(u, none, out=u)
        zf = r @ p["w2"]
        zf += hf
        z[:, :d] = zf.take(order, axis=0)
        # choices, by groups of ids
        nodes = p["odds"].take(tree.columns, axis=0)
        groups = [(i, lo, hi) for i, (lo, hi) in enumerate(zip(borders[:-1], borders[1:])) if lo < hi]
        for i, lo, hi in groups:
            np.matmul(z[lo:hi], nodes[i].T, out=odds[lo:hi])
        s = odds.ravel().take(at)
        s *= signs
        np.minimum(s, most, out=s)
        np.exp(s, out=s)
        s += 1
        laid.ravel()[at] = np.divide(push, s, out=s)
        laid[:, -1] = 0  # the node that fills up never learns
        slopes = np.zeros_like(nodes)
        for i, lo, hi in groups:
            own = laid[lo:hi]
            np.matmul(own, nodes[i][:, :d], out=dz[lo:hi])
            np.matmul(own.T, z[lo:hi], out=slopes[i])
        laid.fill(0)
        slopes = slopes.reshape(-1, d + 1)
        g["odds"][:-1] = slopes.take(tree.first, axis=0)
        if len(tree.shared):
            g["odds"][tree.shared] = tree.whole @ slopes
        dzf = dz.take(back, axis=0)
        dr = dzf @ p["w2"].T
        dr *= np.ceil(np.minimum(r, one))  # 1 where r is above 0
        dhf = dr @ p["w1"].T
        dhf += dzf
        np.matmul(r.T, dzf, out=g["w2"])
        np.matmul(hf.T, dr, out=g["w1"])
        np.matmul(every, dr, out=g["b1"])
        dh = dhf.reshape(b, BLOCK, d)
        dl = dh @ v.transpose(0, 2, 1)
        dl *= a
        dlf = dl.reshape(-1, wide)
        own = dlf @ ones
        own *= af
        dlf -= own
        g["near"][:, 0] = (every[:, :b] @ dl.reshape(b, -1) @ self.by_distance)[0]
        dq = (dl @ k).reshape(-1, d)
        dq *= scale
        dk, dv = (dl.transpose(0, 2, 1) @ q).reshape(-1, d), (a.transpose(0, 2, 1) @ dh).reshape(-1, d)
        de = dk @ p["k"].T
        de += dv @ p["v"].T
        own = de.reshape(b, wide, d)[:, BLOCK:]
        dhf += dq @ p["q"].T
        own += dh
        np.matmul(ef.T, dq, out=g["q"])
        np.matmul(e2f.T, dk, out=g["k"])
        np.matmul(e2f.T, dv, out=g["v"])
        # Adagrad
        slope = self.slope
        self.squares += slope * slope
        slope *= RATE
        slope /= np.sqrt(self.squares)
        self.vector -= slope
        return de


def layout(texts: list[np.ndarray], end: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(blocks, targets, alone) of texts given as ids with the end id last; targets and alone of every block but the first.

    Each text starts with a block of padding, then the end id, as what comes before its first id.
    """
    sizes = np.array([-(-len(t) // BLOCK) for t in texts])
    starts = np.cumsum(sizes + 1) - sizes - 1
    total = int((sizes + 1).sum())
    inputs = np.full(total * BLOCK, end, np.int32)
    targets = np.full(total * BLOCK, -1, np.int32)
    for start, ids in zip((starts * BLOCK + BLOCK).tolist(), texts):
        inputs[start + 1 : start + len(ids)] = ids[:-1]
        targets[start : start + len(ids)] = ids
    lead = np.zeros(total, bool)
    lead[starts] = True
    return inputs.reshape(-1, BLOCK), targets.reshape(-1, BLOCK)[1:], lead[:-1]


def log10_of(model: Model, texts: list[np.ndarray]) -> np.ndarray:
    """log10 probability of each text given as ids with the end id last; windows go through in groups."""
    if not texts:
        return np.empty(0)
    blocks, targets, alone = layout(texts, model.end)
    out = np.empty(targets.shape)
    per = CHUNK // BLOCK
    for at in range(0, len(targets), per):
        part = slice(at, at + per)
        out[part] = model.log10(blocks[at : at + per + 1], targets[part], alone[part]).reshape(-1, BLOCK)
    sizes = np.array([-(-len(t) // BLOCK) + 1 for t in texts])
    return np.add.reduceat(np.concatenate([[0.0], out.sum(axis=1)]), np.cumsum(sizes) - sizes)


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, c) over the texts of ``docs``; the end of a text is the empty word.  Runs of documents are counted before the exchange."""

    def run(batches):
        def told(counted):
            words = list(counted)
            for at in range(0, len(words), 50_000):
                part = words[at : at + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.binary()), pa.array([counted[w] for w in part], pa.int64())], names=["word", "n"])

        counted: Counter = Counter()
        for batch in batches:
            for text in texts_as_bytes(batch.column(0)):
                counted.update(words_of(text))
                counted[_END] += 1
                if len(counted) > RUN_WORDS:
                    yield from told(counted)
                    counted = Counter()
        yield from told(counted)

    return docs.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("c"))


def _id_counts(words: DataFrame, source) -> np.ndarray:
    """Counts of subword ids over a table (word, c); one small vector comes from each task."""

    def run(batches):
        own, total = _ids(source), None
        for batch in batches:
            words, c = batch.column(0).to_pylist(), batch.column(1).to_numpy()
            if total is None:
                total = np.zeros(own.end + 1, np.int64)
            for at in range(0, len(words), 50_000):
                part, weight = words[at : at + 50_000], c[at : at + 50_000]
                ends = np.array([w == _END for w in part])
                total[own.end] += weight[ends].sum()
                ids, lengths, _ = own.of([w for w in part if w != _END])
                total += np.bincount(ids, np.repeat(weight[~ends], lengths), len(total)).astype(np.int64)
        if total is not None:
            some = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(total[some])], names=["id", "n"])

    found = words.mapInArrow(run, "id int, n long").groupBy("id").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros(_ids(source).end + 1, np.int64)
    counts[found["id"].to_numpy()] = found["n"].to_numpy()
    return counts


def spans_of(words: list[bytes], chosen: np.ndarray, ids: Ids) -> np.ndarray:
    """Windows (n, SPAN) of the chosen runs of a text; the last run has the end id, too."""
    out = []
    for r in chosen.tolist():
        lead = max(0, r * RUN - BLOCK - 1)  # enough words for the context of the run's first id
        flat, lengths, _ = ids.of(words[lead : (r + 1) * RUN])
        own = int(lengths[r * RUN - lead :].sum())
        before = flat[: len(flat) - own][-BLOCK - 1 :]
        if (r + 1) * RUN >= len(words):
            flat, own = np.append(flat, ids.end), own + 1
        # a text's first id stands after the end id; of a run further on, after the ids before it
        head = np.concatenate([np.full(BLOCK, -1), [ids.end]]) if not r else np.concatenate([np.full(BLOCK + 1 - len(before), -1), before])
        row = np.concatenate([head, flat[len(flat) - own :], np.full(-own % BLOCK, -1)]).astype(np.int32)
        out.append(np.lib.stride_tricks.sliding_window_view(row, SPAN)[::BLOCK])
    return np.concatenate(out) if out else np.empty((0, SPAN), np.int32)


def windows_of_ids(texts: list[np.ndarray], end: int) -> np.ndarray:
    """All windows (n, SPAN) of texts given as ids with the end id last, cut where scoring cuts them."""
    sizes = np.array([-(-len(t) // BLOCK) for t in texts], np.int64)
    # a text takes a block of nothing, its blocks, and one that only ends the last window
    borders = np.concatenate([[0], np.cumsum(sizes + 2)])
    row = np.full(int(borders[-1] + 1) * BLOCK + 1, -1, np.int32)
    for start, ids in zip((borders[:-1] * BLOCK + BLOCK).tolist(), texts):
        row[start] = end
        row[start + 1 : start + 1 + len(ids)] = ids
    own = np.ones(borders[-1], bool)
    own[borders[1:] - 1] = own[borders[1:] - 2] = False
    return np.lib.stride_tricks.sliding_window_view(row, SPAN)[::BLOCK][: len(own)][own]


def windows_of(texts: list[bytes | None], ids: Ids) -> np.ndarray:
    """Windows (n, SPAN) of texts; the targets of all are the texts' ids with their end ids, each once."""
    found = [np.empty((0, SPAN), np.int32)]
    if SHARE == 1:
        for at in range(0, len(texts), 200):
            found.append(windows_of_ids(ids.texts([words_of(t) for t in texts[at : at + 200]])[0], ids.end))
        return np.concatenate(found)
    for text in texts:
        words = words_of(text)
        runs = np.arange(max(1, -(-len(words) // RUN)))
        hashed = mix(runs.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(xxhash.xxh3_64_intdigest(text or b"")))
        found.append(spans_of(words, np.flatnonzero(hashed % np.uint64(SHARE) == 0), ids))
    return np.concatenate(found)


def dealt_texts(docs: DataFrame) -> DataFrame:
    """(pick, text): the texts of ``docs`` (id, text), and a hash that deals them, copies apart."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.xxhash64("id", text).bitwiseAND((1 << 63) - 1).alias("pick"), text.alias("span"))


def _learned(spans: DataFrame, model: Model, number: int, cut) -> DataFrame:
    """(name, row, n, change): what one round's rows (part, pick, span) teach, averaged over the parts."""
    context = spans.sparkSession.sparkContext
    sent = context.broadcast(model)
    kinds = "name string, row int, n double, change binary"

    def told(rows):
        for at in range(0, len(rows), 5000):
            columns = zip(*rows[at : at + 5000])
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.string(), pa.int32(), pa.float64(), pa.binary()))], names=["name", "row", "n", "change"])

    class Pupil:
        """A copy of the model that learns from one part."""

        def __init__(self, part):
            self.given = given = sent.value
            self.seed, self.held, self.size = (number * 1_000_003 + part) * 1_009, [], 0
            self.model = Model.__new__(Model)
            self.model.__dict__ = {**given.__dict__, "p": {k: v.copy() for k, v in given.p.items()}, "sums": {k: v.copy() for k, v in given.sums.items()}}
            self.uses = {k: np.zeros(len(v)) for k, v in given.p.items()}

        def take(self, value):
            self.held.append(value)
            self.size += len(value)
            if self.size >= MIXED:
                self.study()

        def study(self):
            for name, (used, n) in self.model.train(cut(self.held), self.seed).items():
                self.uses[name][used] += n
            self.seed, self.held, self.size = self.seed + 1, [], 0

        def changes(self):
            self.study()
            rows = []
            for name, uses in self.uses.items():
                used = np.flatnonzero(uses)
                change = np.concatenate([self.model.p[name][used] - self.given.p[name][used], self.model.sums[name][used] - self.given.sums[name][used]], axis=1)
                rows += [(name, r, c, x.tobytes()) for r, c, x in zip(used.tolist(), uses[used].tolist(), change)]
            return rows

    def run(batches):
        work_alone()
        part, pupil = None, None
        for batch in batches:
            for p, value in zip(batch.column(0).to_pylist(), texts_as_bytes(batch.column(2))):
                if p != part:
                    if pupil:
                        yield from told(pupil.changes())
                    part, pupil = p, Pupil(p)
                pupil.take(value)
        if pupil:
            yield from told(pupil.changes())

    def average(batches):
        n = {k: np.zeros(len(v)) for k, v in sent.value.p.items()}
        total = {k: np.zeros((len(v), 2 * v.shape[1])) for k, v in sent.value.p.items()}
        for batch in batches:
            names, rows, weight = np.array(batch.column(0).to_pylist()), batch.column(1).to_numpy(), batch.column(2).to_numpy()
            held = batch.column(3).to_pylist()
            for name in set(names.tolist()):
                at = np.flatnonzero(names == name)
                change = np.frombuffer(b"".join([held[i] for i in at]), np.float32).reshape(len(at), -1)
                np.add.at(n[name], rows[at], weight[at])
                np.add.at(total[name], rows[at], change * weight[at, None])
        rows = []
        for name, uses in n.items():
            used = np.flatnonzero(uses)
            rows += [(name, r, c, x.tobytes()) for r, c, x in zip(used.tolist(), uses[used].tolist(), (total[name][used] / uses[used, None]).astype(np.float32))]
        yield from told(rows)

    parts = spans.sortWithinPartitions("part", "pick", "span").mapInArrow(run, kinds)
    return parts.repartition(8, "name", "row").mapInArrow(average, kinds)


def dealt_parts(windows: DataFrame, parts: int) -> DataFrame:
    """Rows with the round and the part that ``pick`` deals them to; in whole numbers, as doubles hold 53 bits of a pick alone."""
    return windows.withColumn("round", F.col("pick") % ROUNDS).withColumn("part", F.expr(f"cast((pick div {ROUNDS}) % {max(1, parts)} as int)"))


def fit(windows: DataFrame, model: Model, cut=None, count: int | None = None) -> None:
    """Train the model in rounds over all rows (pick, span).

    A span is a window, or what ``cut`` makes windows (n, SPAN) of, given a list; ``count`` is about the
    number of windows.
    """
    cut = cut or (lambda held: np.frombuffer(b"".join(held), np.int32).reshape(-1, SPAN))
    count = windows.count() if count is None else count
    parts = -(-count // (ROUNDS * PART)) if count else 0
    dealt = dealt_parts(windows, parts)
    for number in range(ROUNDS if count else 0):
        spans = dealt.where(F.col("round") == number).select("part", "pick", "span").repartition(parts, "part")
        for name, row, _, change in _learned(spans, model, number, cut).collect():  # no more rows than the model has
            both = np.frombuffer(change, np.float32)
            model.p[name][row] += both[: len(both) // 2]
            model.sums[name][row] += both[len(both) // 2 :]


def score(docs: DataFrame, vocabulary: str, key: str = "doc_id", text: str = "text", name: str = "scoring") -> DataFrame:
    """(key, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row.

    Tokens are words and one end.  Null and empty texts have the end alone.  Keys are integers; rows
    that repeat a key are scored one by one, and a null key is never held out.  Without training
    documents every count is 0 and the weights stay as they were drawn.  Other columns are not read.
    ``vocabulary``: path of a file of ranked byte strings, read on the driver.
    """
    spark = docs.sparkSession
    work = Workspace(spark, name)
    source = spark.sparkContext.broadcast(read_vocabulary(vocabulary))
    own = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    learned_from = own.where(~held_out(FOLDS, HELD_OUT, "id"))

    known = work.keep(word_counts(learned_from), "words")
    ends = F.sum(F.when(F.length("word") == 0, F.col("c")))
    total, distinct, texts_learned = known.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*"), F.coalesce(ends, F.lit(0))).first()

    # the commonest words: those from a count on that leaves COMMON rows at most
    grade = F.floor(F.log2("c") * 8).cast("int")
    graded, rows, least = known.groupBy(grade.alias("g")).count().collect(), 0, 1 << 30  # a few hundred rows
    for r in sorted(graded, key=lambda r: -r.g):
        rows += r["count"]
        least = r.g if rows <= COMMON else least
    top = known.where(grade >= least).toPandas()
    common = {bytes(w): int(c) for w, c in zip(top["word"], top["c"]) if len(w)}
    counted = _id_counts(known, source)
    model = Model(counted, _ids(source).end)
    fit(dealt_texts(learned_from), model, lambda texts: windows_of(texts, _ids(source)), -(-int(counted.sum()) // BLOCK))
    model.ready()
    model.sums = None
    sent = spark.sparkContext.broadcast((model, common))

    def run(batches):
        work_alone()
        m, counts = sent.value
        ids_of = _ids(source, counts)
        end = math.log10(texts_learned + 1)
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                lists = [words_of(t) for t in texts_as_bytes(part.column(1))]
                texts, c = ids_of.texts(lists)
                sizes = np.array([*map(len, lists)], np.int64)
                starts = np.cumsum(sizes) - sizes
                held = c > 0
                summed = lambda x: np.add.reduceat(np.append(x, 0), starts) * (sizes > 0)
                rest = [[words[i] for i in np.flatnonzero(~held[s : s + len(words)]).tolist()] for s, words in zip(starts, lists)]
                columns = [pa.array(log10_of(m, texts)), pa.array(sizes + 1), pa.array(summed(held.astype(np.int64)) + (texts_learned > 0)), pa.array(summed(np.log10(c + 1.0)) + end), pa.array(rest, pa.list_(pa.binary()))]
                yield pa.RecordBatch.from_arrays([part.column(0), *columns], names=["id", "score", "n_tokens", "n_common", "logs", "rest"])

    total = int(total)
    columns = "id long, score double, n_tokens long, n_common long, logs double, rest array<binary>"
    scored = work.keep(own.mapInArrow(run, columns).withColumn("row", F.monotonically_increasing_id()), "scored")
    each = scored.select("row", F.explode("rest").alias("word")).join(known, "word")
    sums = each.groupBy("row").agg(F.sum(F.log10(F.col("c") + 1.0)).alias("more"), F.count("*").alias("n_rare"))
    zero = lambda c: F.coalesce(c, F.lit(0))
    return scored.drop("rest").join(sums, "row", "left").select(
        F.col("id").alias(key),
        held_out(FOLDS, HELD_OUT, "id").alias("held_out"),
        "n_tokens",
        (F.col("n_common") + zero("n_rare")).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("logs") + zero("more") - F.col("n_tokens") * F.lit(math.log10(total + int(distinct) + 1))).alias("base_score"),
        "score",
    )


def standard_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def op9_lm_scoring(spark, sf_dir: str) -> DataFrame:
    """Base and model scores of every document."""
    return score(table(spark, sf_dir, "documents", "doc_id", "text"), standard_ranks(), name="op9")
