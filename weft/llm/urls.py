"""URL filter: host-suffix and path-prefix expressions joined with rules on short hash prefixes.

Each URL is expanded into the expressions a rule could have: suffixes of its host at label
borders times prefixes of its path.  Expressions and rules meet in an equi-join on the first
32 bits of their SHA-256; full digests confirm, and of the rules that fit the longest wins
(host and path together; block before allow where two rules have the same expression).
DataFrame functions only.

Which prefixes are made depends on the rules alone (their most labels, their longest path and
the lengths of those that don't end in a slash), so the work for one URL is bounded by the
rules, however long the URL is, and nothing that a rule could match is left out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import LOWER_LETTERS, UPPER_LETTERS, table

#: Rules of the standard query as (host, path, verdict).
STANDARD_RULES = [
    ("net", "/", "block"),
    ("example.net", "/en/", "allow"),
    ("example.com", "/de/", "block"),
    ("org", "/fr/", "allow"),
]

#: A rule table of up to so many rows is sent to every executor; a larger one is joined by a shuffle.
BROADCAST_RULES = 200_000
#: Lots that rows without a host are spread over.
LOTS = 256


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL; both empty for null or where there is no ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), UPPER_LETTERS, LOWER_LETTERS)
    path = F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)?", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def expressions(host: Column, path: Column, most_labels: int, longest_path: int, odd_lengths: list[int]) -> Column:
    """Array of ``host + NUL + path`` texts that a rule could have, for one URL."""
    labels = F.split(host, r"\.", -1)
    take = F.least(F.size(labels), F.lit(most_labels))
    suffixes = F.transform(F.sequence(F.lit(1), take), lambda n: F.array_join(F.slice(labels, -n, n), "."))
    seen = F.substring(path, 1, longest_path)
    parts = F.split(seen, "/", -1)
    # a prefix that ends in each slash; the last part is what follows the last slash
    slashed = F.when(
        F.size(parts) > 1,
        F.transform(F.sequence(F.lit(1), F.size(parts) - 1), lambda n: F.concat(F.array_join(F.slice(parts, 1, n), "/"), F.lit("/"))),
    ).otherwise(F.array().cast("array<string>"))
    odd = F.array(*[F.when(F.length(path) >= n, F.substring(path, 1, n)) for n in odd_lengths]).cast("array<string>")
    prefixes = F.array_distinct(F.array_compact(F.concat(F.array(F.lit("")), slashed, odd)))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, F.lit("\0"), p))))


def judge(pages: DataFrame, rules: DataFrame, key: str = "page_id", url: str = "url", default: str = "allow") -> DataFrame:
    """One row per row of ``pages``: ``key``, host, path, rule, verdict.

    ``rules``: (host, path, verdict); a rule fits its host and all subdomains if the URL's path
    starts with the rule's.  ``rule`` is host and path of the winning rule, null where none fits;
    the verdict is then ``default``.  Rules with a null host, path or verdict fit nothing; of equal
    rules with both verdicts, block holds.  Null keys and repeated rows keep one result row each.
    Columns other than ``key`` and ``url`` are not read, whatever their names.
    """
    rules = (
        rules.select(F.translate("host", UPPER_LETTERS, LOWER_LETTERS).alias("rule_host"), F.col("path").alias("rule_path"), F.col("verdict").alias("rule_verdict"))
        .dropna()
        .groupBy("rule_host", "rule_path")
        .agg(F.max("rule_verdict").alias("rule_verdict"))  # block sorts after allow
    )
    labels, longest, count, odd = rules.agg(
        F.max(F.size(F.split("rule_host", r"\.", -1))),
        F.max(F.length("rule_path")),
        F.count("*"),
        F.sort_array(F.collect_set(F.when(~F.endswith("rule_path", F.lit("/")) & (F.length("rule_path") > 0), F.length("rule_path")))),
    ).first()
    host, path = host_and_path(F.col(url))
    rows = pages.select(F.col(key).alias("_key"), host.alias("_host"), path.alias("_path"))
    digest = F.sha2(F.concat("rule_host", F.lit("\0"), "rule_path"), 256)
    known = rules.select(
        F.substring(digest, 1, 8).alias("_short"), digest.alias("_full"), F.concat("rule_host", "rule_path").alias("_rule"), "rule_verdict"
    )
    if count <= BROADCAST_RULES:
        known = F.broadcast(known)
    # a URL's own number ties its expressions together again: equal rows share one outcome, so (host, path) serves
    # rows without a host, which may be many, are spread over lots
    lot = F.when(F.col("_host") == "", F.pmod(F.xxhash64("_key"), F.lit(LOTS))).otherwise(F.lit(0).cast("long"))
    rows, lots = rows.withColumn("_lot", lot), F.when(F.col("_host") == "", F.sequence(F.lit(0).cast("long"), F.lit(LOTS - 1).cast("long"))).otherwise(F.array(F.lit(0).cast("long")))
    distinct = rows.select("_host", "_path").distinct()
    made = distinct.select(
        "_host", "_path", F.explode(expressions(F.col("_host"), F.col("_path"), labels or 1, longest or 0, odd or [])).alias("_text")
    ).select("_host", "_path", F.sha2("_text", 256).alias("_digest"))
    best = (
        made.withColumn("_short", F.substring("_digest", 1, 8))
        .join(known, "_short")
        .where("_digest = _full")
        .groupBy("_host", "_path")
        .agg(F.max(F.struct(F.length("_rule").alias("n"), "_rule", "rule_verdict")).alias("_best"))
    )
    best = best.select("_host", "_path", F.explode(lots).alias("_lot"), "_best")
    return rows.join(best, ["_host", "_path", "_lot"], "left").select(
        F.col("_key").alias(key),
        F.col("_host").alias("host"),
        F.col("_path").alias("path"),
        F.col("_best._rule").alias("rule"),
        F.coalesce("_best.rule_verdict", F.lit(default)).alias("verdict"),
    )


def op4_url_filter(spark, sf_dir: str) -> DataFrame:
    """Verdict of the standard rules on every URL of ``pages``."""
    values = ", ".join(f"('{host}', '{path}', '{verdict}')" for host, path, verdict in STANDARD_RULES)
    rules = spark.sql(f"SELECT * FROM VALUES {values} AS rules(host, path, verdict)")
    return judge(table(spark, sf_dir, "pages", "page_id", "url"), rules)


OP4_SQL = r"""
WITH rules(rh, rp, rv) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'),
                                  ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
cut AS (SELECT row_number() OVER () AS n, page_id,
               CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT n, page_id,
                 translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                 regexp_extract(rest, '^[^/?#]*(/[^?#]*)?', 1) AS path FROM cut),
fits AS (SELECT n, max({'l': length(rh || rp), 'r': rh || rp, 'v': rv}) AS b FROM parts, rules
         WHERE (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY n)
SELECT page_id, host, path, b.r AS rule, coalesce(b.v, 'allow') AS verdict FROM parts LEFT JOIN fits USING (n)
"""
