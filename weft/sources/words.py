"""Word builders: any ordered rows, arrays, markup or text lines as a corpus (element, word_id, symbols).

``from_rows`` also has a long form that keeps (element, word_id, position, symbol) rows: profiles are
aggregated from those directly, so a word of a billion symbols never becomes one array.
"""

from __future__ import annotations

from html.parser import HTMLParser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _text(column) -> Column:
    return (F.col(column) if isinstance(column, str) else column).cast("string")


def long_rows(rows: DataFrame, element, word, order_by: list, symbol) -> DataFrame:
    """(element, word_id, position, symbol): ``position`` is a struct of the ordering columns, compared in order."""
    keys = [F.col(c) if isinstance(c, str) else c for c in order_by]
    return rows.select(_text(element).alias("element"), _text(word).alias("word_id"), F.struct(*[k.alias(f"k{i}") for i, k in enumerate(keys)]).alias("position"), _text(symbol).alias("symbol"))


def from_rows(rows: DataFrame, element, word, order_by: list, symbol) -> DataFrame:
    """Rows grouped to words; rows with a null symbol count for the word but give no symbol."""
    held = F.when(F.col("symbol").isNotNull(), F.struct("position", "symbol"))
    grouped = long_rows(rows, element, word, order_by, symbol).groupBy("element", "word_id").agg(F.array_sort(F.collect_list(held)).alias("s"))
    return grouped.select("element", "word_id", F.transform("s", lambda x: x["symbol"]).alias("symbols"))


def from_arrays(rows: DataFrame, element, word, symbols) -> DataFrame:
    array = F.col(symbols) if isinstance(symbols, str) else symbols
    return rows.select(_text(element).alias("element"), _text(word).alias("word_id"), array.cast("array<string>").alias("symbols"))


def tags(pages: DataFrame, element: str = "page") -> DataFrame:
    """Opening tags of raw markup in document order, lower-cased; one word per page."""
    found = F.regexp_extract_all("html", F.lit("<([a-zA-Z][a-zA-Z0-9]*)"), F.lit(1))
    return pages.select(F.lit(element).alias("element"), F.col("page_id").cast("string").alias("word_id"), F.coalesce(F.transform(found, F.lower), F.array().cast("array<string>")).alias("symbols"))


#: Markup elements that never have children, and those whose end tag may be missing.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
IMPLIED = {"p": {"p", "div", "ul", "ol", "table", "h1", "h2", "h3", "article", "footer", "nav"}, "li": {"li"}, "option": {"option"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}}


class _Children(HTMLParser):
    """Ordered child tags of every element of one page."""

    def __init__(self):
        super().__init__()
        self.open: list[tuple[str, list[str]]] = [("#root", [])]
        self.done: list[tuple[str, list[str]]] = []

    def handle_starttag(self, tag, attrs):
        if tag in IMPLIED.get(self.open[-1][0], ()):
            self.done.append(self.open.pop())
        self.open[-1][1].append(tag)
        if tag in VOID:
            self.done.append((tag, []))
        else:
            self.open.append((tag, []))

    def handle_startendtag(self, tag, attrs):
        self.open[-1][1].append(tag)
        self.done.append((tag, []))

    def handle_endtag(self, tag):
        if any(name == tag for name, _ in self.open[1:]):
            while self.open[-1][0] != tag:
                self.done.append(self.open.pop())
            self.done.append(self.open.pop())


def child_sequences(html: str | None) -> list[tuple[str, list[str]]]:
    """(parent tag, child tags) of every element of one page; the page itself is ``#root``."""
    reader = _Children()
    reader.feed(html or "")
    reader.close()
    return reader.done + reader.open[::-1]


def children(pages: DataFrame) -> DataFrame:
    """One word per element of every page: its child tags, under the element's own tag."""

    def run(batches):
        import pandas as pd

        for batch in batches:
            rows = []
            for page, html in zip(batch["page_id"], batch["html"]):
                rows += [(tag, f"{page}/{i}", kids) for i, (tag, kids) in enumerate(child_sequences(html))]
            yield pd.DataFrame(rows, columns=["element", "word_id", "symbols"])

    return pages.select("page_id", "html").mapInPandas(run, "element string, word_id string, symbols array<string>")


#: Shapes of a line, the first that fits counts.
SHAPES = [
    ("mail", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}"),
    ("url", r"https?://"),
    ("license", r"(?i)licen[sc]e|copyright|all rights reserved"),
    ("blank", r"^\s*$"),
    ("run", r"(\S+)( \1){3,}"),
    ("sentence", r"[.!?]\s*$"),
]


def line_shapes(texts: DataFrame, element="doc", key: str = "doc_id", text: str = "text") -> DataFrame:
    """The shape of every line of a text, by the first rule of ``SHAPES`` that fits; ``short`` if none does."""

    def shape(line: Column) -> Column:
        out = F.lit("short")
        for name, pattern in reversed(SHAPES):
            out = F.when(line.rlike(pattern), F.lit(name)).otherwise(out)
        return out

    lines = F.split(F.coalesce(F.col(text), F.lit("")), "\n")
    name = F.lit(element) if isinstance(element, str) else element
    return texts.select(name.cast("string").alias("element"), F.col(key).cast("string").alias("word_id"), F.transform(lines, shape).alias("symbols"))


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Event types of each user's sessions: runs of events with pauses shorter than ``gap``."""
    timed = events.select(F.col("user_id").cast("string").alias("element"), F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    grouped = timed.groupBy("element", F.session_window("ts", gap).alias("w")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("s"))
    return grouped.select("element", F.concat_ws("/", "element", F.col("w.start").cast("string")).alias("word_id"), F.transform("s", lambda x: x["event_type"]).alias("symbols"))


def top_dims(vectors: DataFrame, k: int = 6) -> DataFrame:
    """The ``k`` largest dimensions of each vector, descending, under its label; every symbol at most once."""
    ranked = F.slice(F.array_sort(F.transform("embedding", lambda x, i: F.struct((-x).alias("v"), i.alias("i")))), 1, k)
    return vectors.select(F.col("label").cast("string").alias("element"), F.col("vec_id").cast("string").alias("word_id"), F.transform(ranked, lambda s: F.concat(F.lit("d"), s["i"].cast("string"))).alias("symbols"))


def json_keys(rows: DataFrame, element, word, column: str) -> DataFrame:
    """Top-level keys of a JSON object, in order."""
    return rows.select(_text(element).alias("element"), _text(word).alias("word_id"), F.coalesce(F.json_object_keys(column), F.array().cast("array<string>")).alias("symbols"))
