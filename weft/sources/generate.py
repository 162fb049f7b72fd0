"""Words with a known layout, from hashes of given keys: the same words on any number of partitions."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.schema import Schema, parse
from .draws import Draws

#: Layouts of six kinds of bibliographic records, symbols as numbers.
PLANTED = {
    "inproceedings": "1* 12? 5* 9? 18? 15* & 3 6 11* & 4 & 13* & 14* & 19*",
    "article": "1* 17? 5* 12? 15* & 3 6 11? & 8 & 9? & 10? & 13* & 14*",
    "proceedings": "2* 3+ 18? 21? 8? 10? 13? 12? 15* 19? 7? 9? & 4? & 6 & 11? & 17? & 20*",
    "incollection": "1* 3 4 17? 20? 16? 11? 15* 14? & 13? 19? & 5? & 6",
    "phdthesis": "1 3 6 17? 21? 20? 9? 13? 12? & 22",
    "www": "1* 2* 3 4? 6? 11",
}

#: Least and greatest count that is drawn for each multiplicity.
DRAWN = {"1": (1, 1), "?": (0, 1), "*": (0, 3), "+": (1, 3)}


def planted(keys: DataFrame, key: str, layouts: dict[str, str] = PLANTED) -> DataFrame:
    """One word of every layout for each key.

    A symbol's count is drawn from a hash of key, layout and symbol.  Factors interleave by sorting
    symbols by hash-drawn moments that grow along each factor, so every merge can occur.  Keys are dealt
    evenly first: a small table of keys makes a large table of words.
    """
    parsed_layouts = {name: parse(text) for name, text in layouts.items()}

    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            draws = Draws(ids)
            for name, factors in parsed_layouts.items():
                yield pa.RecordBatch.from_arrays([pa.repeat(pa.scalar(name), len(ids)), ids, _symbols(draws, name, factors)], ["element", "word_id", "symbols"])

    parts = int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return keys.select(F.col(key).cast("string").alias("word_id")).repartition(parts).mapInArrow(run, "element string, word_id string, symbols array<string>")


def _symbols(draws: Draws, name: str, factors: Schema) -> pa.Array:
    """The word of one layout for each key: a copy's moment is its place in its factor plus a share of a step, in what one draw leaves of the word."""
    starts = [draws(f"{name}/factor {i}") for i in range(len(factors))]
    # copies at one moment stand by place, then by symbol
    slots = sorted((j, symbol, i, mult) for i, factor in enumerate(factors) for j, (symbol, mult) in enumerate(factor))
    moments, names = [], []
    for j, symbol, i, mult in slots:
        low, high = DRAWN[mult]
        copies = low + np.floor(draws(f"{name}/{symbol}") * (high - low + 1)).astype(int) if low < high else None
        for k in range(high):
            held = None if copies is None or k < low else copies > k
            moment = starts[i] + (1 - starts[i]) * ((j + (k + draws(f"{name}/{symbol}/{k}", held)) / 4.0) / len(factors[i]))
            moments.append(moment if held is None else np.where(held, moment, np.inf))
            names.append(symbol)
    at = np.stack(moments, axis=1)
    sizes = np.isfinite(at).sum(axis=1)
    order = np.argsort(at, axis=1, kind="stable")[np.arange(at.shape[1]) < sizes[:, None]]
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(names).take(pa.array(order)))


def planted_sql(keys: str, key: str, layouts: dict[str, str] = PLANTED) -> str:
    """SELECT (element, word_id, symbols) with the words of ``planted``."""
    rows = ", ".join(f"('{name}', {i}, {j}, {len(factor)}, '{s}', {DRAWN[m][0]}, {DRAWN[m][1]})" for name, text in layouts.items() for i, factor in enumerate(parse(text)) for j, (s, m) in enumerate(factor))
    draw = lambda part: f"((('0x' || substr(md5({key} || '/' || element || '/' || {part}), 1, 7))::INTEGER % 1000)::DOUBLE / 1000::DOUBLE)"
    return f"""SELECT element, {key}::VARCHAR AS word_id, list(s ORDER BY b + (1 - b) * ((j + (k + {draw("s || '/' || k")}) / 4::DOUBLE) / n), j, s) AS symbols
FROM (SELECT *, unnest(range(0, copies)) AS k FROM (SELECT *, low + floor({draw("s")} * (high - low + 1))::INTEGER AS copies, {draw("'factor ' || i")} AS b
      FROM (SELECT {key} FROM {keys} WHERE {key} IS NOT NULL), (VALUES {rows}) layout(element, i, j, n, s, low, high))) GROUP BY element, {key}"""


def from_words(spark: SparkSession, words: Iterable[tuple[str, str]]) -> DataFrame:
    """A corpus of (element, word) with one letter per symbol."""
    rows = [(e, str(i), list(w)) for i, (e, w) in enumerate(words)]
    return spark.createDataFrame(rows, "element string, word_id string, symbols array<string>")


#: Worked samples, one letter per symbol.
EXAMPLES = {
    "one_word": ["abcd"],
    "two_words": ["abcd", "dabc"],
    "rivals": ["abcd", "adbc"],
    "repeats": ["abcd", "aadbc", "bdd"],
    "broken_path": ["xabcdy", "cda"],
    "revisit": ["acab"],
    "cyclic": ["ab", "bc", "ca"],
    "empty_and_one": ["", "a"],
    "single_letters": ["a", "aa"],
}


def examples(spark: SparkSession) -> DataFrame:
    return from_words(spark, [(name, w) for name, ws in EXAMPLES.items() for w in ws])


def words_from_graph(vertices: DataFrame, edges: DataFrame, element: str = "graph") -> DataFrame:
    """A corpus whose conflict graph is the given one: two opposite words per edge, one word per vertex without edges.

    ``vertices`` (v), ``edges`` (x, y).  Shows that learning smallest schemas is as hard as repeated
    maximum independent sets.
    """
    lone = vertices.join(edges.select(F.col("x").alias("v")).union(edges.select(F.col("y").alias("v"))).distinct(), "v", "left_anti")
    both = edges.select(F.explode(F.array(F.array("x", "y"), F.array("y", "x"))).alias("symbols"))
    return both.union(lone.select(F.array("v").alias("symbols"))).select(F.lit(element).alias("element"), F.array_join("symbols", "|").alias("word_id"), "symbols")


def parsed(layouts: dict[str, str] = PLANTED) -> dict[str, Schema]:
    return {name: parse(text) for name, text in layouts.items()}
