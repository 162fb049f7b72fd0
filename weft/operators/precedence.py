"""Precedence between symbols: profiles, pairs, conflicts, stable order.

A symbol x stands before y somewhere in a word exactly when x's first place is before y's last, so
a word matters only through the first place, last place and (capped) count of its distinct
symbols: its profile.  Words with equal profiles are merged before pairs are made, which is what
keeps the pairs bounded by the alphabet and not by the data.  Everything here is a union, a
minimum or a maximum, so partial aggregation is exact and hot elements are spread by signature.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import batches


def profile(words: DataFrame) -> DataFrame:
    """(element, word_id, prof array<struct<s, f, l, c>>) of a corpus: per distinct symbol first and last place and count.

    Works inside each row; no shuffle.
    """
    symbols = F.col("symbols")
    prof = F.transform(
        F.array_sort(F.array_distinct(symbols)),
        lambda s: F.struct(
            s.alias("s"),
            F.array_position(symbols, s).cast("int").alias("f"),
            (F.size(symbols) + 1 - F.array_position(F.reverse(symbols), s)).cast("int").alias("l"),
            F.size(F.filter(symbols, lambda x: x == s)).alias("c"),
        ),
    )
    return words.select("element", "word_id", prof.alias("prof"))


def profile_from_rows(rows: DataFrame) -> DataFrame:
    """The same from long rows (element, word_id, position, symbol), words never being materialised.

    Rows with a null symbol keep an otherwise empty word.  Places are ranks among the word's own
    first and last places, which preserve every comparison.
    """
    per_symbol = rows.groupBy("element", "word_id", "symbol").agg(F.min("position").alias("f"), F.max("position").alias("l"), F.count("*").cast("int").alias("c"))
    held = F.when(F.col("symbol").isNotNull(), F.struct(F.col("symbol").alias("s"), "f", "l", "c"))
    per_word = per_symbol.groupBy("element", "word_id").agg(F.array_sort(F.collect_list(held)).alias("p"))
    places = F.array_sort(F.array_distinct(F.concat(F.transform("p", lambda x: x["f"]), F.transform("p", lambda x: x["l"]))))
    ranked = per_word.select("element", "word_id", "p", F.explode(F.array(places)).alias("places"))
    rank = lambda x: F.array_position("places", x).cast("int")
    return ranked.select("element", "word_id", F.transform("p", lambda x: F.struct(x["s"].alias("s"), rank(x["f"]).alias("f"), rank(x["l"]).alias("l"), x["c"].alias("c"))).alias("prof"))


def signatures(profiles: DataFrame) -> DataFrame:
    """(element, prof, n_words): distinct profiles up to order-preserving places and counts capped at two.

    The exchange is on element and profile together, so an element that holds most words is spread.
    """
    places = F.array_sort(F.array_distinct(F.concat(F.transform("prof", lambda x: x["f"]), F.transform("prof", lambda x: x["l"]))))
    ranked = profiles.select("element", "prof", F.explode(F.array(places)).alias("places"))
    rank = lambda x: F.array_position("places", x).cast("int")
    short = F.transform("prof", lambda x: F.struct(x["s"].alias("s"), rank(x["f"]).alias("f"), rank(x["l"]).alias("l"), F.least(x["c"], F.lit(2)).alias("c")))
    return ranked.select("element", short.alias("prof")).groupBy("element", "prof").agg(F.count("*").alias("n_words"))


def word_pairs(prof: Column) -> Column:
    """Pairs (x, y), x other than y, with x before y somewhere in the word of this profile."""
    return F.flatten(F.transform(prof, lambda a: F.transform(F.filter(prof, lambda b: (a["s"] != b["s"]) & (a["f"] < b["l"])), lambda b: F.struct(a["s"].alias("x"), b["s"].alias("y")))))


def pairs_of(signed: DataFrame) -> DataFrame:
    """(element, x, y, n_words) from signatures."""
    each = signed.select("element", "n_words", F.explode(word_pairs(F.col("prof"))).alias("p"))
    return each.groupBy("element", F.col("p.x").alias("x"), F.col("p.y").alias("y")).agg(F.sum("n_words").alias("n_words"))


def pairs(words: DataFrame, plan: str = "profile") -> DataFrame:
    """Precedence pairs of a corpus with the number of words that have each.

    ``plan``: ``profile`` (default), ``batches`` (no merging of words first: for corpora nearly all of
    whose words differ), ``selfjoin`` (profiles joined with themselves), or ``positions`` (every pair of
    places; the definition itself, quadratic in a word's length).
    """
    if plan == "profile":
        return pairs_of(signatures(profile(words)))
    if plan == "batches":
        seen = batches.counts(words).where("kind = 'pair'").groupBy("element", "u", "v").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
        ways = F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("y"), F.col("up").alias("n_words")), F.struct(F.col("v").alias("x"), F.col("u").alias("y"), F.col("down").alias("n_words")))
        return seen.select("element", F.explode(ways).alias("p")).select("element", "p.*").where("n_words > 0")
    if plan == "selfjoin":
        flat = profile(words).select("element", "word_id", F.explode("prof").alias("p"))
        a = flat.select("element", "word_id", F.col("p.s").alias("x"), F.col("p.f").alias("f"))
        b = flat.select("element", "word_id", F.col("p.s").alias("y"), F.col("p.l").alias("l"))
        return a.join(b, ["element", "word_id"]).where("x <> y and f < l").groupBy("element", "x", "y").agg(F.count("*").alias("n_words"))
    if plan == "positions":
        flat = words.select("element", "word_id", F.posexplode("symbols").alias("i", "s"))
        a, b = (flat.select("element", "word_id", F.col("i").alias(n), F.col("s").alias(s)) for n, s in (("i", "x"), ("j", "y")))
        return a.join(b, ["element", "word_id"]).where("i < j and x <> y").select("element", "word_id", "x", "y").distinct().groupBy("element", "x", "y").agg(F.count("*").alias("n_words"))
    raise ValueError(f"no such plan: {plan}")


def directed(precedence: DataFrame) -> DataFrame:
    """(element, x, y, conflict) with x < y in conflicts, else the one direction seen; one aggregate, no self-join."""
    both = precedence.groupBy("element", F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).agg(F.bool_or(F.col("x") < F.col("y")).alias("up"), F.bool_or(F.col("x") > F.col("y")).alias("down"))
    up, conflict = F.col("up"), F.col("up") & F.col("down")
    return both.select("element", F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"), conflict.alias("conflict"))


def conflicts(precedence: DataFrame) -> DataFrame:
    """(element, x, y): pairs whose reverse is a pair too, in both directions."""
    one = directed(precedence).where("conflict").select("element", "x", "y")
    return one.union(one.select("element", F.col("y").alias("x"), F.col("x").alias("y")))


def stable(precedence: DataFrame) -> DataFrame:
    """(element, x, y): pairs of one direction only."""
    return directed(precedence).where("not conflict").select("element", "x", "y")


def conflict_graph(precedence: DataFrame) -> DataFrame:
    """(element, edges): one undirected edge per conflict, smaller symbol first."""
    found = directed(precedence).where("conflict")
    return found.groupBy("element").agg(F.array_sort(F.collect_list(F.struct("x", "y"))).alias("edges"))


def multiplicities_of(signed: DataFrame) -> DataFrame:
    """(element, symbol, min_n, max_n, in_words, words, mult) from signatures; counts are capped at two."""
    words = signed.groupBy("element").agg(F.sum("n_words").alias("words"))
    each = signed.select("element", "n_words", F.explode("prof").alias("p"))
    seen = each.groupBy("element", F.col("p.s").alias("symbol")).agg(F.min("p.c").alias("least"), F.max("p.c").alias("most"), F.sum("n_words").alias("in_words"))
    return _multiplicities(seen.join(words, "element"))


def _multiplicities(seen: DataFrame) -> DataFrame:
    least = F.when(F.col("in_words") < F.col("words"), 0).otherwise(F.col("least")).cast("long")
    out = seen.select("element", "symbol", least.alias("min_n"), F.col("most").cast("long").alias("max_n"), "in_words", "words")
    return out.withColumn("mult", mult(F.col("min_n"), F.col("max_n")))


def mult(least: Column, most: Column) -> Column:
    """Operator for counts between ``least`` and ``most``: none seen or one, one or more, any."""
    return F.when(least == 0, F.when(most > 1, "*").otherwise("?")).otherwise(F.when(most > 1, "+").otherwise("1"))


def multiplicities(words: DataFrame, plan: str = "profile") -> DataFrame:
    """Counts of each symbol; ``plan`` as for ``pairs``."""
    if plan == "profile":
        return multiplicities_of(signatures(profile(words)))
    if plan != "batches":
        raise ValueError(f"no such plan: {plan}")
    counted = batches.counts(words).where("kind <> 'pair'").groupBy("element", "kind", "u").agg(F.sum("n").alias("n"), F.min("least").alias("least"), F.max("most").alias("most"))
    is_symbol = F.col("kind") == "symbol"
    listed = counted.where("element is not null").groupBy("element").agg(F.max(F.when(~is_symbol, F.col("n"))).alias("words"), F.collect_list(F.when(is_symbol, F.struct(F.col("u").alias("symbol"), "least", "most", F.col("n").alias("in_words")))).alias("s"))
    return _multiplicities(listed.select("element", "words", F.explode("s").alias("s")).select("element", "words", "s.*"))


def adjacency(words: DataFrame, plan: str = "profile") -> DataFrame:
    """(element, x, y, n_words): y directly after x in some word; x and y may be equal.  ``plan`` as for ``pairs``."""
    if plan == "batches":
        return batches.adjacency(words).groupBy("element", "x", "y").agg(F.sum("n_words").alias("n_words"))
    after = F.when(F.size("symbols") > 1, F.arrays_zip(F.slice("symbols", 1, F.size("symbols") - 1).alias("x"), F.slice("symbols", 2, F.size("symbols")).alias("y")))
    each = words.select("element", F.explode(F.array_distinct(after)).alias("p"))
    return each.groupBy("element", "p.x", "p.y").agg(F.count("*").alias("n_words"))
