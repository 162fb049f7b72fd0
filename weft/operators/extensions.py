"""Beyond the learners: groups of exclusive symbols, and precedence with a minimum support."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import baselines, measures, precedence, validate


def exclusive_pairs(corpus: DataFrame) -> DataFrame:
    """(element, x, y) with x < y: symbols that never share a word."""
    symbols = corpus.select("element", F.explode(F.array_distinct("symbols")).alias("s")).groupBy("element").agg(F.array_sort(F.collect_set("s")).alias("s"))
    every = symbols.select("element", F.explode(F.flatten(F.transform("s", lambda a: F.transform(F.filter("s", lambda b: a < b), lambda b: F.struct(a.alias("x"), b.alias("y")))))).alias("p"))
    return every.select("element", "p.x", "p.y").join(baselines.together(corpus), ["element", "x", "y"], "left_anti")


def choices_in_factors(corpus: DataFrame, schemas: DataFrame) -> DataFrame:
    """(element, learner, choices, text): schemas whose factors may hold choices.

    Neighbours of a factor that pairwise never share a word become one choice, grown from the left: a
    word holds one of them at most, so the order between them says nothing.  A choice is required when
    some member is in every word, and repeats when a member does.  The sample stays accepted.
    """
    apart = exclusive_pairs(corpus).groupBy("element").agg(F.collect_set(F.concat_ws("\0", "x", "y")).alias("apart"))
    held = precedence.multiplicities(corpus).groupBy("element").agg(F.collect_list(F.struct("symbol", "max_n", "in_words", "words")).alias("held"))

    def run(batches):
        import pandas as pd

        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                never = set(r.apart) if r.apart is not None else set()
                count = {h["symbol"]: h for h in (r.held if r.held is not None else [])}
                factors, choices = [], 0
                for f in measures._values(r.factors):
                    groups: list[list[str]] = []
                    for s, _ in f:
                        if groups and all("\0".join(sorted((s, t))) in never for t in groups[-1]):
                            groups[-1].append(s)
                        else:
                            groups.append([s])
                    shown = []
                    for g in groups:
                        many = any(count[s]["max_n"] > 1 for s in g)
                        always = sum(count[s]["in_words"] for s in g) == count[g[0]]["words"]
                        name = g[0] if len(g) == 1 else "(" + "|".join(sorted(g)) + ")"
                        choices += len(g) > 1
                        shown.append(name + (("+" if many else "") if always else ("*" if many else "?")))
                    factors.append(" ".join(shown))
                out.append((r.element, r.learner, choices, " & ".join(factors)))
            yield pd.DataFrame(out, columns=["element", "learner", "choices", "text"])

    rows = schemas.select("element", "learner", validate.flat(F.col("factors")).alias("factors")).join(apart, "element", "left").join(held, "element", "left")
    return rows.mapInPandas(run, "element string, learner string, choices long, text string")


def frequent_precedence(corpus: DataFrame, min_support: float = 0.5) -> DataFrame:
    """(element, x, y, support): precedence pairs in at least that share of the words."""
    words = corpus.groupBy("element").agg(F.count("*").alias("words"))
    out = precedence.pairs(corpus).join(words, "element")
    return out.select("element", "x", "y", F.round(F.col("n_words") / F.col("words"), 6).alias("support")).where(F.col("support") >= min_support)


def closed_precedence(frequent: DataFrame) -> DataFrame:
    """(element, x, y, support): pairs that no chain x, z, y of equal support makes redundant."""
    a = frequent.select("element", "x", F.col("y").alias("z"), F.col("support").alias("s1"))
    b = frequent.select("element", F.col("x").alias("z"), "y", F.col("support").alias("s2"))
    implied = a.join(b, ["element", "z"]).where("x <> y").select("element", "x", "y", F.least("s1", "s2").alias("s"))
    best = implied.groupBy("element", "x", "y").agg(F.max("s").alias("s"))
    return frequent.join(best, ["element", "x", "y"], "left").where(F.col("s").isNull() | (F.col("s") < F.col("support"))).drop("s")


def frequent_by_projection(corpus: DataFrame, element: str, min_support: float = 0.5) -> DataFrame:
    """(element, x, y, support): the frequent pairs of one element by the library's prefix-projected mining, to compare with."""
    from pyspark.ml.fpm import PrefixSpan

    own = corpus.where(F.col("element") == element)
    words = own.count()
    sequences = own.select(F.transform("symbols", lambda s: F.array(s)).alias("sequence"))
    found = PrefixSpan(minSupport=min_support, maxPatternLength=2, sequenceCol="sequence").findFrequentSequentialPatterns(sequences)
    x, y = F.col("sequence")[0][0], F.col("sequence")[1][0]
    pairs = found.where(F.size("sequence") == 2).where(x != y)
    return pairs.select(F.lit(element).alias("element"), x.alias("x"), y.alias("y"), F.round(F.col("freq") / words, 6).alias("support"))
