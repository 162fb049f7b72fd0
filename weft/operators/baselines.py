"""Baselines: schemas without interleaving, without order, or with order by majority."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..types import SCHEMA
from . import batches, graphs, precedence


def star(corpus: DataFrame) -> DataFrame:
    """(element, alphabet, words, text): one repeated choice of the whole alphabet, as declared schemas often are."""
    symbols = corpus.select("element", F.explode(F.array_distinct("symbols")).alias("s")).groupBy("element").agg(F.array_sort(F.collect_set("s")).alias("alphabet"))
    words = corpus.groupBy("element").agg(F.count("*").alias("words"))
    out = words.join(symbols, "element", "left").withColumn("alphabet", F.coalesce("alphabet", F.array().cast("array<string>")))
    return out.select("element", "alphabet", "words", F.concat(F.lit("("), F.array_join("alphabet", "|"), F.lit(")*")).alias("text"))


def multiplicities_only(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """Schema rows with every symbol a factor of its own: counts, no order."""
    counts = precedence.multiplicities(corpus, plan)
    grouped = counts.groupBy("element").agg(F.max("words").alias("words"), F.array_sort(F.collect_list(F.struct("symbol", "mult"))).alias("s"))
    text = F.array_join(F.transform("s", lambda x: F.concat(x["symbol"], F.when(x["mult"] == "1", "").otherwise(x["mult"]))), " & ")
    return grouped.select("element", F.lit("multiplicity").alias("learner"), F.transform("s", lambda x: F.array(x)).alias("factors"), "words", F.lit("ok").alias("status"), F.lit(False).alias("repaired"), text.alias("text"))


def together(corpus: DataFrame) -> DataFrame:
    """(element, x, y, n_words) with x < y: pairs that share a word."""
    each = corpus.select("element", F.array_sort(F.array_distinct("symbols")).alias("s")).groupBy("element", "s").agg(F.count("*").alias("n"))
    pairs = F.flatten(F.transform("s", lambda a: F.transform(F.filter("s", lambda b: a < b), lambda b: F.struct(a.alias("x"), b.alias("y")))))
    return each.select("element", "n", F.explode(pairs).alias("p")).groupBy("element", "p.x", "p.y").agg(F.sum("n").alias("n_words"))


def disjunctive_multiplicities(corpus: DataFrame) -> DataFrame:
    """(element, groups array<struct<symbols, mult>>, text): symbols that never share a word grouped to choices.

    Groups are grown from the smallest symbol on.  A group is required when some member is in every
    word, and repeats when a member does.
    """
    counts = precedence.multiplicities(corpus)
    listed = counts.groupBy("element").agg(F.max("words").alias("words"), F.array_sort(F.collect_list(F.struct("symbol", "max_n", "in_words"))).alias("s"))
    edges = together(corpus).groupBy("element").agg(F.collect_list(F.struct("x", "y")).alias("e"))

    def run(frames):
        import pandas as pd

        for batch in frames:
            out = []
            for row in batch.itertuples(index=False):
                g = graphs.graph([s["symbol"] for s in row.s], [(p["x"], p["y"]) for p in (row.e if row.e is not None else [])])
                groups: list[list[str]] = []
                for s in sorted(g):
                    home = next((x for x in groups if not g[s] & set(x)), None)
                    groups.append([s]) if home is None else home.append(s)
                held = {s["symbol"]: s for s in row.s}
                made = []
                for x in groups:
                    many = any(held[s]["max_n"] > 1 for s in x)
                    always = sum(held[s]["in_words"] for s in x) == row.words
                    made.append({"symbols": x, "mult": ("+" if many else "1") if always else ("*" if many else "?")})
                text = " & ".join(("(" + "|".join(m["symbols"]) + ")" if len(m["symbols"]) > 1 else m["symbols"][0]) + ("" if m["mult"] == "1" else m["mult"]) for m in made)
                out.append((row.element, made, text))
            yield pd.DataFrame(out, columns=["element", "groups", "text"])

    return listed.join(edges, "element", "left").mapInPandas(run, "element string, groups array<struct<symbols:array<string>,mult:string>>, text string")


def ordered_chain(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """(element, factors array<struct<symbols, mult>>, text): a concatenation of choices, without interleaving.

    Symbols that can follow each other in both directions, at any distance of neighbours, form one
    repeated choice; single symbols with equal neighbours are merged; the rest is ordered.  Counts per
    word give each class its operator.  Of the published technique only; other tools' texts may differ.
    ``plan`` as for ``precedence.pairs``.
    """
    neighbours = precedence.adjacency(corpus, plan).groupBy("element").agg(F.collect_list(F.struct("x", "y")).alias("a"))
    seen = corpus.select("element", F.array_sort(F.transform(F.array_distinct("symbols"), lambda s: F.struct(s.alias("s"), F.least(F.size(F.filter("symbols", lambda x: x == s)), F.lit(2)).alias("c")))).alias("w"))
    shapes = (batches.shapes(corpus) if plan == "batches" else seen).groupBy("element", "w").agg(F.count("*").alias("n"))
    alphabet = shapes.select("element", F.explode("w").alias("p")).groupBy("element").agg(F.array_sort(F.collect_set("p.s")).alias("alphabet"))

    def classes(frames):
        import pandas as pd

        for batch in frames:
            out = []
            for row in batch.itertuples(index=False):
                after = {s: set() for s in row.alphabet}
                before = {s: set() for s in row.alphabet}
                for p in row.a if row.a is not None else []:
                    after[p["x"]].add(p["y"])
                    before[p["y"]].add(p["x"])
                groups = graphs._strong(sorted(after), after)
                merged: dict = {}
                for x in groups:
                    key = ("many", x[0]) if len(x) > 1 or x[0] in after[x[0]] else (frozenset(before[x[0]]), frozenset(after[x[0]]))
                    merged.setdefault(key, []).extend(x)
                home = {s: min(x) for x in merged.values() for s in x}
                step = {h: set() for h in home.values()}
                for s, ys in after.items():
                    step[home[s]] |= {home[y] for y in ys} - {home[s]}
                if any(len(c) > 1 for c in graphs._strong(sorted(step), step)):  # merging closed a cycle
                    home = {s: min(x) for x in groups for s in x}
                    step = {h: set() for h in home.values()}
                    for s, ys in after.items():
                        step[home[s]] |= {home[y] for y in ys} - {home[s]}
                place = {h: i for i, h in enumerate(graphs.topological(step, step))}
                out += [(row.element, s, home[s], place[home[s]]) for s in sorted(home)]
            yield pd.DataFrame(out, columns=["element", "s", "home", "place"])

    homes = alphabet.join(neighbours, "element", "left").mapInPandas(classes, "element string, s string, home string, place int")
    # counts of a class in a word: a shape's counts are capped at two, and so is their sum
    each = shapes.withColumn("w_id", F.xxhash64("w")).select("element", "w_id", "n", F.explode("w").alias("p"))
    per_word = each.join(homes, (each["element"] == homes["element"]) & (F.col("p.s") == F.col("s"))).groupBy(each["element"], "w_id", "home", "place").agg(F.sum("p.c").alias("c"), F.max("n").alias("n"))
    totals = shapes.groupBy("element").agg(F.sum("n").alias("words"))
    per_class = per_word.groupBy("element", "home", "place").agg(F.min("c").alias("least"), F.max("c").alias("most"), F.sum("n").alias("in_words"))
    members = homes.groupBy("element", "home").agg(F.array_sort(F.collect_list("s")).alias("symbols"))
    counted = per_class.join(members, ["element", "home"]).join(totals, "element")
    op = precedence.mult(F.when(F.col("in_words") < F.col("words"), 0).otherwise(F.col("least")), F.col("most"))
    factors = counted.groupBy("element").agg(F.array_sort(F.collect_list(F.struct("place", "symbols", op.alias("mult")))).alias("f"))
    shown = F.transform(
        "f",
        lambda x: F.concat(
            F.when(F.size(x["symbols"]) > 1, F.concat(F.lit("("), F.array_join(x["symbols"], "|"), F.lit(")"))).otherwise(F.get(x["symbols"], F.lit(0))), F.when(x["mult"] == "1", "").otherwise(x["mult"])
        ),
    )
    return totals.join(factors, "element", "left").select(
        "element", F.coalesce(F.transform("f", lambda x: F.struct(x["symbols"].alias("symbols"), x["mult"].alias("mult"))), F.array().cast("array<struct<symbols:array<string>,mult:string>>")).alias("factors"), F.coalesce(F.array_join(shown, " "), F.lit("")).alias("text")
    )


def chain_accepts(corpus: DataFrame, chains: DataFrame) -> DataFrame:
    """(element, word_id, accepted) under ``ordered_chain`` schemas, by one regular expression per element.

    Symbols are separated by blanks; they must not hold blanks themselves.
    """
    quoted = lambda s: F.concat(F.lit("\\Q"), s, F.lit("\\E "))
    pattern = F.concat(
        F.lit("^"), F.array_join(F.transform("factors", lambda f: F.concat(F.lit("(?:"), F.array_join(F.transform(f["symbols"], quoted), "|"), F.lit(")"), F.when(f["mult"] == "1", "").otherwise(f["mult"]))), ""), F.lit("$")
    )
    known = chains.select("element", pattern.alias("pattern"))
    word = F.array_join(F.transform("symbols", lambda s: F.concat(s, F.lit(" "))), "")
    return corpus.join(known, "element").select("element", "word_id", F.rlike(word, F.col("pattern")).alias("accepted"))


def global_order(corpus: DataFrame, threshold: float = 0.5) -> DataFrame:
    """(element, x, y, share): x before y in more than ``threshold`` of the words that have both, by first places.

    Unlike the learners, it allows words that violate it.
    """
    prof = precedence.signatures(precedence.profile(corpus))
    first = F.flatten(F.transform("prof", lambda a: F.transform(F.filter("prof", lambda b: a["f"] < b["f"]), lambda b: F.struct(a["s"].alias("x"), b["s"].alias("y")))))
    seen = prof.select("element", "n_words", F.explode(first).alias("p")).groupBy("element", F.col("p.x").alias("x"), F.col("p.y").alias("y")).agg(F.sum("n_words").alias("n"))
    both = seen.groupBy("element", F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).agg(F.sum("n").alias("total"), F.sum(F.when(F.col("x") < F.col("y"), F.col("n")).otherwise(0)).alias("up"))
    up = F.col("up") * 2 >= F.col("total")
    share = F.round(F.greatest(F.col("up"), F.col("total") - F.col("up")) / F.col("total"), 6)
    return both.select("element", F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"), share.alias("share")).where(F.col("share") > threshold)


def star_schema_rows(corpus: DataFrame) -> DataFrame:
    """The star baseline as schema rows: every symbol a factor of its own with ``*``."""
    rows = star(corpus)
    factors = F.transform("alphabet", lambda s: F.array(F.struct(s.alias("symbol"), F.lit("*").alias("mult"))))
    return rows.select("element", F.lit("star").alias("learner"), factors.alias("factors"), "words", F.lit("ok").alias("status"), F.lit(False).alias("repaired"), "text").to(_struct(rows))


def _struct(frame: DataFrame):
    from pyspark.sql.types import StructType

    return StructType.fromDDL(SCHEMA)
