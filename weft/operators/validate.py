"""Membership of words in learned schemas, as a join and three tests on profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .precedence import profile, signatures

def flat(factors: Column) -> Column:
    """Array of (symbol, factor, place, mult) of a schema's factors."""
    return F.flatten(F.transform(factors, lambda f, i: F.transform(f, lambda p, j: F.struct(p["symbol"].alias("symbol"), i.alias("factor"), j.alias("place"), p["mult"].alias("mult")))))


def reason(prof: Column, flat_schema: Column) -> Column:
    """``ok``, ``unknown_symbol``, ``count`` or ``order``, from a word's profile and a flat schema.

    A word is in the language when it has known symbols only, every symbol's count is allowed, and no
    symbol that stands later in a factor comes before an earlier one of the same factor.
    """
    of = lambda s: F.get(F.filter(flat_schema, lambda x: x["symbol"] == s), F.lit(0))
    unknown = F.exists(prof, lambda p: ~F.exists(flat_schema, lambda x: x["symbol"] == p["s"]))
    absent = F.exists(flat_schema, lambda x: x["mult"].isin("1", "+") & ~F.exists(prof, lambda p: p["s"] == x["symbol"]))
    repeated = F.exists(prof, lambda p: (p["c"] > 1) & of(p["s"])["mult"].isin("1", "?"))
    placed = F.transform(prof, lambda p: F.struct(p["f"].alias("f"), p["l"].alias("l"), of(p["s"])["factor"].alias("factor"), of(p["s"])["place"].alias("place")))
    wrong = F.exists(placed, lambda a: F.exists(placed, lambda b: (a["factor"] == b["factor"]) & (a["place"] < b["place"]) & (b["f"] < a["l"])))
    return F.when(unknown, "unknown_symbol").when(absent | repeated, "count").when(wrong, "order").otherwise("ok")


def _judged(profiles: DataFrame, schemas: DataFrame) -> DataFrame:
    """Profiles with the learner and the reason under each schema of their element.

    One row of schemas per element meets the profiles; which side is sent around, and whether an element
    that holds most words is split, is decided at run time by the sizes found.
    """
    known = schemas.groupBy("element").agg(F.collect_list(F.struct("learner", flat(F.col("factors")).alias("flat"))).alias("known"))
    met = profiles.join(known, "element", "left").withColumn("s", F.explode_outer("known"))
    verdict = F.when(F.col("s").isNull(), "no_schema").otherwise(reason(F.col("prof"), F.col("s.flat")))
    return met.withColumn("learner", F.col("s.learner")).withColumn("reason", verdict).drop("known", "s", "prof")


def accepts(words: DataFrame, schemas: DataFrame) -> DataFrame:
    """(element, word_id, learner, accepted, reason) of every word under every schema of its element.

    Words of elements without a schema have one row with no learner, not accepted, for ``no_schema``.
    """
    return _judged(profile(words), schemas).select("element", "word_id", "learner", (F.col("reason") == "ok").alias("accepted"), "reason")


def coverage(words: DataFrame, schemas: DataFrame) -> DataFrame:
    """(element, learner, words, accepted, coverage); distinct signatures are judged, each for all its words."""
    judged = _judged(signatures(profile(words)), schemas)
    accepted = F.sum(F.when(F.col("reason") == "ok", F.col("n_words")).otherwise(0))
    out = judged.groupBy("element", "learner").agg(F.sum("n_words").alias("words"), accepted.alias("accepted"))
    return out.withColumn("coverage", F.round(F.col("accepted") / F.col("words"), 6))
