"""Symbols and pairs of words counted batch by batch, for corpora nearly all of whose words differ.

Where few signatures stand for many words, ``precedence.signatures`` merges words before pairs are made.
Where nearly every word has a signature of its own, merging moves the whole corpus and saves nothing:
here each batch of words gives its counts, and only those are exchanged.  Both ways give the same counts.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: What one batch says of an element's words (kind ``word``), symbols and unordered pairs of symbols (u < v).
COUNTS = "element string, kind string, u string, v string, n long, least int, most int, up long, down long"

#: Pairs of entries that are looked at together.
_PAIRS = 2_000_000


def _codes(values: pa.Array) -> tuple[np.ndarray, list]:
    """Numbers of the values in the order of their texts, null last, and the values."""
    coded = values.dictionary_encode()
    known = coded.dictionary.to_pylist()
    order = sorted(range(len(known)), key=lambda i: known[i].encode())
    rank = np.empty(len(known) + 1, np.int64)
    rank[order] = np.arange(len(known))
    rank[-1] = len(known)
    at = pc.fill_null(coded.indices, len(known)).to_numpy(zero_copy_only=False)
    return rank[at], [*(known[i] for i in order), None]


def entries(symbols: pa.Array) -> tuple[np.ndarray, ...]:
    """(word, symbol, first, last, count, names): the distinct symbols of each word with places from 0; a null symbol's count is 0."""
    lengths = pc.fill_null(pc.list_value_length(symbols), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    code, names = _codes(symbols.flatten())
    word = np.repeat(np.arange(len(lengths)), lengths)
    place = np.arange(len(code)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    key = word * len(names) + code
    order = np.argsort(key, kind="stable")
    key = key[order]
    starts = np.flatnonzero(np.diff(key, prepend=-1))
    ends = np.append(starts[1:], len(key)) - 1
    symbol = key[starts] % len(names)
    count = np.where(symbol == len(names) - 1, 0, ends - starts + 1)
    return key[starts] // len(names), symbol, place[order[starts]] if len(key) else starts, place[order[ends]] if len(key) else starts, count, names


def _tally(keys: np.ndarray, *marks: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct keys, how often each comes, and how often with each mark."""
    found, inverse = np.unique(keys, return_inverse=True)
    return found, [np.bincount(inverse, minlength=len(found)), *(np.bincount(inverse[m], minlength=len(found)) for m in marks)]


def _pairs(element: np.ndarray, word: np.ndarray, symbol: np.ndarray, first: np.ndarray, last: np.ndarray, names: int):
    """Keys (element, u, v) of pairs u < v that share a word, with the words that have u before v and v before u."""
    known = symbol < names - 1
    element, word, symbol, first, last = (x[known] for x in (element, word, symbol, first, last))
    if not len(word):
        return
    starts = np.flatnonzero(np.diff(word, prepend=-1))
    ends = np.append(starts[1:], len(word))
    later = np.repeat(ends, ends - starts) - np.arange(len(word)) - 1  # entries of the same word with a greater symbol
    done = np.cumsum(later)
    cuts = np.searchsorted(done, np.arange(0, done[-1], _PAIRS), side="right").tolist()
    for a, b in zip(cuts, [*cuts[1:], len(word)]):
        n = later[a:b]
        i = np.repeat(np.arange(a, b), n)
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n)
        if len(i):
            yield _tally((element[i] * names + symbol[i]) * names + symbol[j], first[i] < last[j], first[j] < last[i])


def counts(words: DataFrame) -> DataFrame:
    """``COUNTS`` rows of a corpus: those of one element, kind, u and v are still to be added up."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            element, elements = _codes(batch.column(0))
            word, symbol, first, last, count, names = entries(batch.column(1))
            own, found = element[word], []
            e, (n,) = _tally(element)
            found.append((e, "word", None, None, n, None, None, None, None))
            key, (n, none, once) = _tally(own * len(names) + symbol, count == 0, count == 1)
            least, most = np.where(none > 0, 0, np.where(once > 0, 1, 2)), np.where(n > none + once, 2, np.where(once > 0, 1, 0))
            found.append((key // len(names), "symbol", key % len(names), None, n, least, most, None, None))
            for key, (n, up, down) in _pairs(own, word, symbol, first, last, len(names)):
                found.append((key // len(names) ** 2, "pair", key // len(names) % len(names), key % len(names), n, None, None, up, down))
            for e, kind, u, v, n, least, most, up, down in found:
                text = lambda values, codes: pa.nulls(len(n), pa.string()) if codes is None else pa.array(values, pa.string()).take(pa.array(codes))  # noqa: E731, B023
                number = lambda x, kind: pa.nulls(len(n), kind) if x is None else pa.array(x, kind)  # noqa: E731, B023
                yield pa.RecordBatch.from_arrays(
                    [text(elements, e), pa.repeat(pa.scalar(kind), len(n)), text(names, u), text(names, v), number(n, pa.int64()), number(least, pa.int32()), number(most, pa.int32()), number(up, pa.int64()), number(down, pa.int64())],
                    ["element", "kind", "u", "v", "n", "least", "most", "up", "down"],
                )

    return words.select("element", "symbols").mapInArrow(run, COUNTS)


#: Rows of ``shapes``: the symbols of one word and how often each comes, two at most.
SHAPES = "element string, w array<struct<s:string,c:int>>"


def shapes(words: DataFrame) -> DataFrame:
    """(element, w) of every word, in the order of the symbols."""

    def run(batches):
        for batch in batches:
            word, symbol, _, _, count, names = entries(batch.column(1))
            offsets = np.concatenate([[0], np.cumsum(np.bincount(word, minlength=batch.num_rows))]).astype(np.int32)
            w = pa.StructArray.from_arrays([pa.array(names, pa.string()).take(pa.array(symbol)), pa.array(np.minimum(count, 2), pa.int32())], ["s", "c"])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets), w)], ["element", "w"])

    return words.select("element", "symbols").mapInArrow(run, SHAPES)


def _neighbours(symbols: pa.Array) -> tuple[np.ndarray, ...]:
    """(word, inner, code, same, names) of every symbol; ``inner``: not the first of its word, ``same``: a repeat of the one before it."""
    lengths = pc.fill_null(pc.list_value_length(symbols), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    code, names = _codes(symbols.flatten())
    word = np.repeat(np.arange(len(lengths)), lengths)
    inner = np.diff(word, prepend=-1) == 0
    return word, inner, code, inner & (np.diff(code, prepend=-1) == 0), names


def adjacency(words: DataFrame) -> DataFrame:
    """(element, x, y, n_words) of neighbours, those of a batch together; still to be added up."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            element, elements = _codes(batch.column(0))
            word, inner, code, _, names = _neighbours(batch.column(1))
            at = np.flatnonzero(inner)
            once = np.unique((word[at] * len(names) + code[at - 1]) * len(names) + code[at])
            pair = once % len(names) ** 2
            key, (n,) = _tally(element[once // len(names) ** 2] * len(names) ** 2 + pair)
            text = lambda values, codes: pa.array(values, pa.string()).take(pa.array(codes))
            yield pa.RecordBatch.from_arrays(
                [text(elements, key // len(names) ** 2), text(names, key // len(names) % len(names)), text(names, key % len(names)), pa.array(n, pa.int64())], ["element", "x", "y", "n_words"]
            )

    return words.select("element", "symbols").mapInArrow(run, "element string, x string, y string, n_words long")


def collapsed(words: DataFrame) -> DataFrame:
    """(element, word_id, symbols) with runs of a symbol made one."""

    def run(batches):
        for batch in batches:
            word, _, code, same, names = _neighbours(batch.column(2))
            offsets = np.concatenate([[0], np.cumsum(np.bincount(word[~same], minlength=batch.num_rows))]).astype(np.int32)
            symbols = pa.ListArray.from_arrays(pa.array(offsets), pa.array(names, pa.string()).take(pa.array(code[~same])))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), symbols], ["element", "word_id", "symbols"])

    return words.select("element", "word_id", "symbols").mapInArrow(run, "element string, word_id string, symbols array<string>")
