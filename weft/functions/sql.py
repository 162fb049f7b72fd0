"""SQL surface: scalar functions, an aggregate and table functions for the learner's parts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import schema as S


def _accepts(symbols: pd.Series, schema: pd.Series) -> pd.Series:
    return pd.Series([None if w is None or s is None else S.accepts(S.parse(s), list(w)) == "ok" for w, s in zip(symbols, schema)], dtype="object")


def _learn(symbols: pd.Series) -> str:
    from ..operators import graphs

    words = [list(w) for w in symbols if w is not None]
    names = sorted({s for w in words for s in w})
    pairs = {(x, y) for w in {tuple(w) for w in words} for x in set(w) for y in set(w) if x != y and w.index(x) < len(w) - 1 - w[::-1].index(y)}
    conflicts = graphs.graph(names, [p for p in pairs if p[0] < p[1] and p[::-1] in pairs])
    after = {s: {y for x, y in pairs if x == s and (y, x) not in pairs} for s in names}
    counts = {s: [w.count(s) for w in words] for s in names}
    mult = {s: ("*" if max(c) > 1 else "?") if min(c) == 0 else ("+" if max(c) > 1 else "1") for s, c in counts.items()}
    sets = graphs.iterate_sets(conflicts, graphs.auto_independent_set)
    return S.to_text([[(s, mult[s]) for s in graphs.topological(p, after)] for x in sets for p in graphs.cycle_repair(x, after)])


class ChildSequences:
    """Ordered child tags of every element of a page."""

    def eval(self, html: str) -> Iterator[tuple]:
        from ..sources.words import child_sequences

        yield from child_sequences(html)


class ShuffleWords:
    """All merges of two words."""

    def eval(self, u: list, v: list, limit: int) -> Iterator[tuple]:
        for w in S.shuffle_words(list(u), list(v), limit):
            yield (list(w),)


class EnumerateLanguage:
    """Words of a schema up to a length."""

    def eval(self, schema: str, max_len: int) -> Iterator[tuple]:
        for w in S.enumerate_language(S.parse(schema), max_len):
            yield (list(w),)


class BlockOrders:
    """Orders of a schema's symbols as blocks."""

    def eval(self, schema: str) -> Iterator[tuple]:
        for w in S.block_orders(S.parse(schema)):
            yield (list(w),)


class MaximalSets:
    """Maximal independent sets of a graph given as vertices and edges ``x|y``."""

    def eval(self, vertices: list, edges: list) -> Iterator[tuple]:
        from ..operators import graphs

        for s in graphs.maximal_independent_sets(graphs.graph(vertices, [tuple(e.split("|")) for e in edges])):
            yield (s,)


def run_collapse(symbols):
    """Expression: runs of a symbol made one."""
    return F.filter(symbols, lambda s, i: (i == 0) | (s != F.get(symbols, i - 1)))


def register_all(spark: SparkSession) -> None:
    """Functions ``accepts_word(symbols, schema)``, ``learn_schema(symbols)`` (aggregate) and the table functions
    ``child_sequences``, ``shuffle_words``, ``enumerate_language``, ``block_orders``, ``maximal_sets``."""
    spark.udf.register("accepts_word", F.pandas_udf(_accepts, "boolean"))
    learn = F.pandas_udf(_learn, "string", F.PandasUDFType.GROUPED_AGG)
    spark.udf.register("learn_schema", learn)
    for name, cls, columns in (
        ("child_sequences", ChildSequences, "tag string, children array<string>"),
        ("shuffle_words", ShuffleWords, "word array<string>"),
        ("enumerate_language", EnumerateLanguage, "word array<string>"),
        ("block_orders", BlockOrders, "blocks array<string>"),
        ("maximal_sets", MaximalSets, "members array<string>"),
    ):
        spark.udtf.register(name, F.udtf(cls, returnType=columns))


def views(words: DataFrame, prefix: str = "") -> None:
    """Temporary views ``words``, ``precedence``, ``conflicts``, ``stable`` and ``multiplicities`` of a corpus."""
    from ..operators import precedence

    pairs = precedence.pairs(words)
    for name, frame in (("words", words), ("precedence", pairs), ("conflicts", precedence.conflicts(pairs)), ("stable", precedence.stable(pairs)), ("multiplicities", precedence.multiplicities(words))):
        frame.createOrReplaceTempView(prefix + name)
