"""The experiment workloads on the given tables: a builder for each, and the same words in SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sources import generate, words
from .sources.tables import table


def pages(spark: SparkSession, d: str) -> DataFrame:
    """Opening tags of each page."""
    return words.tags(table(spark, d, "pages", "page_id", "html"))


def page_children(spark: SparkSession, d: str) -> DataFrame:
    """Child tags of each element of each page, by parent tag."""
    return words.children(table(spark, d, "pages", "page_id", "html"))


def conversations(spark: SparkSession, d: str) -> DataFrame:
    """Roles of each conversation by turn."""
    return words.from_rows(table(spark, d, "conversations", "conv_id", "turn", "role"), F.lit("conversation"), "conv_id", ["turn", "role"], "role")


def _events(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    return rows.withColumn("day", F.concat_ws("/", F.col("user_id").cast("string"), F.to_date("ts").cast("string")))


def events(spark: SparkSession, d: str) -> DataFrame:
    """Event types of each user and day, all under one element."""
    return words.from_rows(_events(spark, d), F.lit("events"), "day", ["ts", "event_id"], "event_type")


def events_rows(spark: SparkSession, d: str) -> DataFrame:
    """The same as long rows."""
    return words.long_rows(_events(spark, d), F.lit("events"), "day", ["ts", "event_id"], "event_type")


def users(spark: SparkSession, d: str) -> DataFrame:
    """Event types of each day, by user."""
    return words.from_rows(_events(spark, d), "user_id", "day", ["ts", "event_id"], "event_type")


def customers(spark: SparkSession, d: str) -> DataFrame:
    """Priorities of each year's orders, by customer."""
    rows = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    rows = rows.withColumn("y", F.concat_ws("/", F.col("o_custkey").cast("string"), F.year("o_orderdate").cast("string")))
    return words.from_rows(rows, "o_custkey", "y", ["o_orderdate", "o_orderkey"], "o_orderpriority")


def segments(spark: SparkSession, d: str) -> DataFrame:
    """Priorities of each customer's orders, by market segment."""
    rows = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority").join(table(spark, d, "customer", "c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    return words.from_rows(rows, "c_mktsegment", "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderpriority")


def lineitem_rows(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_shipdate", "l_returnflag", "l_linestatus")
    return words.long_rows(rows, F.lit("lineitem"), "l_orderkey", ["l_shipdate", "l_linenumber", F.concat("l_returnflag", "l_linestatus")], F.concat("l_returnflag", "l_linestatus"))


def lineitem(spark: SparkSession, d: str) -> DataFrame:
    """Return flag and status of each order's lines by ship date."""
    rows = table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_shipdate", "l_returnflag", "l_linestatus").withColumn("s", F.concat("l_returnflag", "l_linestatus"))
    return words.from_rows(rows, F.lit("lineitem"), "l_orderkey", ["l_shipdate", "l_linenumber", "s"], "s")


def planted(spark: SparkSession, d: str) -> DataFrame:
    """Words of six planted layouts, seeded by order keys."""
    return generate.planted(table(spark, d, "orders", "o_orderkey").where("o_orderkey is not null"), "o_orderkey")


def documents(spark: SparkSession, d: str) -> DataFrame:
    """Line shapes of each document."""
    return words.line_shapes(table(spark, d, "documents", "doc_id", "text"))


def benchmark(spark: SparkSession, d: str) -> DataFrame:
    """Line shapes of each benchmark item, under the element of the documents."""
    return words.line_shapes(table(spark, d, "benchmark", "item_id", "text"), key="item_id")


def qualities(spark: SparkSession, d: str) -> DataFrame:
    """Line shapes of labelled documents, by quality."""
    rows = table(spark, d, "documents", "doc_id", "text").join(table(spark, d, "labels", "doc_id", "quality"), "doc_id")
    return words.line_shapes(rows, F.concat(F.lit("quality "), F.col("quality").cast("string")))


def dims(spark: SparkSession, d: str) -> DataFrame:
    """Six largest dimensions of each vector, by label."""
    return words.top_dims(table(spark, d, "embeddings", "vec_id", "embedding", "label"))


def brands(spark: SparkSession, d: str) -> DataFrame:
    """Part types of each order by line, by the customer's region; small dimensions join by broadcast when Spark finds them small."""
    rows = (
        table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linenumber")
        .join(table(spark, d, "part", "p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
        .join(table(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(table(spark, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
        .join(table(spark, d, "nation", "n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(table(spark, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    )
    return words.from_rows(rows, "r_name", "l_orderkey", ["l_linenumber", "p_type"], "p_type")


def part_brands(spark: SparkSession, d: str) -> DataFrame:
    """Brands of each order's lines by the supplier's region: 25 symbols, one word for an order and region."""
    lines = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    rows = (
        lines.join(table(spark, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
        .join(table(spark, d, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
        .join(table(spark, d, "nation", "n_nationkey", "n_regionkey"), F.col("s_nationkey") == F.col("n_nationkey"))
        .join(table(spark, d, "region", "r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
        .withColumn("word", F.concat_ws("/", F.col("l_orderkey").cast("string"), "r_name"))
    )
    return words.from_rows(rows, "r_name", "word", ["l_linenumber", "p_brand"], "p_brand")


def languages(spark: SparkSession, d: str) -> DataFrame:
    """Line shapes of each document, by language."""
    return words.line_shapes(table(spark, d, "documents", "doc_id", "text", "lang").where("lang is not null"), F.col("lang"))


def toxicities(spark: SparkSession, d: str) -> DataFrame:
    """Line shapes of labelled documents, by toxicity."""
    rows = table(spark, d, "documents", "doc_id", "text").join(table(spark, d, "labels", "doc_id", "toxic"), "doc_id")
    return words.line_shapes(rows, F.concat(F.lit("toxic "), F.col("toxic").cast("string")))


def props(spark: SparkSession, d: str) -> DataFrame:
    """Keys of the events' JSON properties."""
    return words.json_keys(table(spark, d, "events", "event_id", "event_type", "props"), "event_type", "event_id", "props")


def sessions(spark: SparkSession, d: str) -> DataFrame:
    """Event types of each user's sessions."""
    return words.sessions(table(spark, d, "events", "event_id", "ts", "user_id", "event_type"))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "pages": pages,
    "page_children": page_children,
    "conversations": conversations,
    "events": events,
    "users": users,
    "customers": customers,
    "segments": segments,
    "lineitem": lineitem,
    "planted": planted,
    "documents": documents,
    "qualities": qualities,
    "dims": dims,
    "brands": brands,
    "part_brands": part_brands,
    "languages": languages,
    "toxicities": toxicities,
    "props": props,
    "sessions": sessions,
}

#: A line's shape, the first that fits: a run is a word three times more after a word that ends with it, the last as a beginning.
_SHAPE = r"""CASE WHEN regexp_matches(x, '[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}') THEN 'mail' WHEN contains(x, 'http://') OR contains(x, 'https://') THEN 'url'
  WHEN regexp_matches(x, '(?i)licen[sc]e|copyright|all rights reserved') THEN 'license' WHEN regexp_matches(x, '^\s*$') THEN 'blank'
  WHEN len(list_filter(range(1, len(v) - 2), lambda i: v[i + 1] = v[i + 2] AND regexp_matches(v[i + 1], '^\S+$') AND ends_with(v[i], v[i + 1]) AND starts_with(v[i + 3], v[i + 1]))) > 0 THEN 'run'
  WHEN regexp_matches(x, '[.!?]\s*$') THEN 'sentence' ELSE 'short' END"""


def _shapes(element: str, rows: str, key: str = "doc_id") -> str:
    lines = f"SELECT {element} AS element, {key}::VARCHAR AS word_id, unnest(string_split(coalesce(text, ''), chr(10))) AS x, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS no FROM {rows}"
    return f"SELECT element, word_id, list({_SHAPE} ORDER BY no) AS symbols FROM (SELECT *, string_split(x, ' ') AS v FROM ({lines})) GROUP BY element, word_id"


#: SELECT (element, word_id, symbols) for the workloads that SQL can build.
SQL = {
    "pages": "SELECT 'page' AS element, page_id::VARCHAR AS word_id, list_transform(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1), lambda t: lower(t)) AS symbols FROM pages",
    "conversations": "SELECT 'conversation' AS element, conv_id::VARCHAR AS word_id, list(role ORDER BY turn, role) AS symbols FROM conversations GROUP BY conv_id",
    "events": "SELECT 'events' AS element, user_id || '/' || ts::DATE AS word_id, list(event_type ORDER BY ts, event_id) AS symbols FROM events GROUP BY user_id, ts::DATE",
    "users": "SELECT user_id::VARCHAR AS element, user_id || '/' || ts::DATE AS word_id, list(event_type ORDER BY ts, event_id) AS symbols FROM events GROUP BY user_id, ts::DATE",
    "customers": "SELECT o_custkey::VARCHAR AS element, o_custkey || '/' || year(o_orderdate) AS word_id, list(o_orderpriority ORDER BY o_orderdate, o_orderkey) AS symbols FROM orders GROUP BY o_custkey, year(o_orderdate)",
    "segments": "SELECT c_mktsegment AS element, o_custkey::VARCHAR AS word_id, list(o_orderpriority ORDER BY o_orderdate, o_orderkey) AS symbols FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment, o_custkey",
    "lineitem": "SELECT 'lineitem' AS element, l_orderkey::VARCHAR AS word_id, list(l_returnflag || l_linestatus ORDER BY l_shipdate, l_linenumber, l_returnflag || l_linestatus) AS symbols FROM lineitem GROUP BY l_orderkey",
    "brands": "SELECT r_name AS element, l_orderkey::VARCHAR AS word_id, list(p_type ORDER BY l_linenumber, p_type) AS symbols FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, l_orderkey",
    "dims": "SELECT label::VARCHAR AS element, vec_id::VARCHAR AS word_id, list('d' || i ORDER BY v DESC, i)[1:6] AS symbols FROM (SELECT vec_id, label, unnest(embedding) AS v, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY label, vec_id",
    "props": "SELECT event_type AS element, event_id::VARCHAR AS word_id, json_keys(props) AS symbols FROM events",
    "part_brands": "SELECT r_name AS element, l_orderkey || '/' || r_name AS word_id, list(p_brand ORDER BY l_linenumber, p_brand) AS symbols FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, l_orderkey",
    "documents": _shapes("'doc'", "documents"),
    "languages": _shapes("lang", "documents WHERE lang IS NOT NULL"),
    "qualities": _shapes("'quality ' || quality", "documents JOIN labels USING (doc_id) WHERE quality IS NOT NULL"),
    "toxicities": _shapes("'toxic ' || toxic", "documents JOIN labels USING (doc_id) WHERE toxic IS NOT NULL"),
    "planted": generate.planted_sql("orders", "o_orderkey"),
    "benchmark": _shapes("'doc'", "benchmark", "item_id"),
    "sessions": """SELECT user_id::VARCHAR AS element, user_id || '/' || strftime(min(ts), '%Y-%m-%d %H:%M:%S') || CASE WHEN microsecond(min(ts)) % 1000000 = 0 THEN '' ELSE '.' || rtrim(lpad((microsecond(min(ts)) % 1000000)::VARCHAR, 6, '0'), '0') END AS word_id, list(event_type ORDER BY ts, event_id) AS symbols
      FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS no FROM (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, no""",
}
