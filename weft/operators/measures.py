"""Cost, quality and accuracy measures of learned schemas."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import schema as S
from . import precedence, validate


def sizes(factors: Column) -> Column:
    """Factor sizes, descending."""
    return F.transform(F.array_sort(F.transform(factors, lambda f: -F.size(f))), lambda n: -n)


def interleavings(schemas: DataFrame) -> DataFrame:
    """(element, learner, interleavings): factors less one; none for an empty schema."""
    return schemas.select("element", "learner", F.greatest(F.size("factors") - 1, F.lit(0)).cast("long").alias("interleavings"))


def simplified(schemas: DataFrame) -> DataFrame:
    """(element, learner, sizes): factor sizes, descending, as text."""
    return schemas.select("element", "learner", F.array_join(F.transform(sizes(F.col("factors")), lambda n: n.cast("string")), ",").alias("sizes"))


def gap(schemas: DataFrame, reference: str = "exact") -> DataFrame:
    """(element, learner, more_factors, first_difference): against the reference learner's schema.

    ``first_difference``: at the first place where the size vectors differ, the reference's size less
    the learner's; 0 for equal vectors.
    """
    own = schemas.select("element", "learner", sizes(F.col("factors")).alias("a"))
    base = own.where(F.col("learner") == reference).select("element", F.col("a").alias("b"))
    differences = F.zip_with("b", "a", lambda x, y: F.coalesce(x, F.lit(0)) - F.coalesce(y, F.lit(0)))
    first = F.coalesce(F.get(F.filter(differences, lambda d: d != 0), F.lit(0)), F.lit(0)).cast("long")
    return own.where(F.col("learner") != reference).join(base, "element").select("element", "learner", (F.size("a") - F.size("b")).cast("long").alias("more_factors"), first.alias("first_difference"))


def learner_table(schemas: DataFrame) -> DataFrame:
    """Learners as columns: interleavings and factor sizes of every element, side by side."""
    flat = interleavings(schemas).join(simplified(schemas), ["element", "learner"])
    return flat.groupBy("element").pivot("learner", ["exact", "is", "dag"]).agg(F.first("interleavings").alias("n"), F.first("sizes").alias("sizes"))


def sample_sizes(corpus: DataFrame) -> DataFrame:
    """(element, words, distinct_words, signatures); only hashes of words are moved."""
    prof = precedence.profile(corpus)
    signed = precedence.signatures(prof).groupBy("element").agg(F.count("*").alias("signatures"), F.sum("n_words").alias("words"))
    distinct = corpus.select("element", F.xxhash64("symbols").alias("a"), F.hash("symbols").alias("b")).distinct().groupBy("element").agg(F.count("*").alias("distinct_words"))
    return signed.join(distinct, "element").select("element", "words", "distinct_words", "signatures")


def conflict_density(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """(element, symbols, conflict_pairs, density): unordered pairs in conflict over all unordered pairs; ``plan`` as for ``precedence.pairs``."""
    if plan == "batches":
        from ..plans.learn import relations

        rows = relations(corpus, plan).where(F.size("symbols") > 0)
        known = F.filter("symbols", lambda s: s["symbol"].isNotNull())
        out = rows.select("element", F.size(known).cast("long").alias("symbols"), F.size("conflicts").cast("long").alias("conflict_pairs"))
    else:
        signed = precedence.signatures(precedence.profile(corpus))
        n = signed.select("element", F.explode("prof.s").alias("s")).groupBy("element").agg(F.count_distinct("s").alias("symbols"))
        k = precedence.directed(precedence.pairs_of(signed)).where("conflict").groupBy("element").agg(F.count("*").alias("conflict_pairs"))
        out = n.join(k, "element", "left").select("element", "symbols", F.coalesce("conflict_pairs", F.lit(0)).alias("conflict_pairs"))
    pairs = F.col("symbols") * (F.col("symbols") - 1) / 2
    return out.withColumn("density", F.round(F.when(pairs > 0, F.col("conflict_pairs") / pairs).otherwise(0.0), 6))


def log_orders(schemas: DataFrame) -> DataFrame:
    """(element, learner, log_orders, orders): orders of all symbols once each that a schema accepts.

    The logarithm is a sum inside the plan; ``orders`` is the exact number, as text.
    """
    log_factorial = lambda n: F.aggregate(F.sequence(F.lit(0), n), F.lit(0.0), lambda s, i: s + F.when(i > 1, F.ln(i.cast("double"))).otherwise(0.0))
    per = sizes(F.col("factors"))
    total = F.aggregate(per, F.lit(0), lambda s, n: s + n)
    log = log_factorial(total) - F.aggregate(F.transform(per, log_factorial), F.lit(0.0), lambda s, x: s + x)
    exact = F.udf(lambda n: str(S.orders_accepted(n)), "string")  # numbers beyond any column type; one small row per schema
    return schemas.select("element", "learner", F.round(log, 6).alias("log_orders"), exact(per).alias("orders"))


def _flat(column: str = "factors") -> Column:
    return validate.flat(F.col(column))


def _values(flat) -> S.Schema:
    """Factors from a flat schema; factors come in order, and symbols in their factor's order."""
    out: S.Schema = []
    for p in flat:
        if p["place"] == 0:
            out.append([])
        out[-1].append((p["symbol"], p["mult"]))
    return out


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """(element, a, b, relation) of the languages of two learners' schemas of each element."""

    def run(batches):
        import pandas as pd

        for batch in batches:
            yield pd.DataFrame(
                [(r.element, r.a, r.b, S.compare(_values(r.fa), _values(r.fb))) for r in batch.itertuples(index=False)], columns=["element", "a", "b", "relation"]
            )

    left = a.select("element", F.col("learner").alias("a"), _flat().alias("fa"))
    right = b.select("element", F.col("learner").alias("b"), _flat().alias("fb"))
    return left.join(right, "element").mapInPandas(run, "element string, a string, b string, relation string")


def compare_chain(schemas: DataFrame, chains: DataFrame) -> DataFrame:
    """(element, learner, relation) of each schema's language to that of the chain baseline of its element."""

    def run(batches):
        import pandas as pd

        for batch in batches:
            rows = [(r.element, r.learner, S.compare_with_chain(_values(r.f), [(list(c["symbols"]), c["mult"]) for c in r.chain])) for r in batch.itertuples(index=False)]
            yield pd.DataFrame(rows, columns=["element", "learner", "relation"])

    known = chains.select("element", F.col("factors").alias("chain"))
    return schemas.select("element", "learner", _flat().alias("f")).join(known, "element").mapInPandas(run, "element string, learner string, relation string")


def minimality(schemas: DataFrame, graph_rows: DataFrame) -> DataFrame:
    """(element, learner, minimal): no schema of the class fits strictly between the sample and this one."""

    def run(batches):
        import pandas as pd

        from ..plans.learn import _graphs

        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                _, conflicts, after = _graphs(r)
                out.append((r.element, r.learner, S.is_inclusion_minimal(_values(r.factors), after, conflicts)))
            yield pd.DataFrame(out, columns=["element", "learner", "minimal"])

    return schemas.select("element", "learner", _flat().alias("factors")).join(graph_rows, "element").mapInPandas(run, "element string, learner string, minimal boolean")


def length(schemas: DataFrame) -> DataFrame:
    """(element, learner, tokens, block_tokens): length of the expression, and of its written-out block orders.

    The written-out form has orders! / product of sizes! alternatives of all symbols each, joined by bars.
    """

    def run(batches):
        import pandas as pd

        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                f = _values(r.factors)
                per = sum(1 + (m != "1") for x in f for _, m in x)
                n = S.orders_accepted(map(len, f))
                out.append((r.element, r.learner, S.tokens(f), float(n * per + n - 1)))
            yield pd.DataFrame(out, columns=["element", "learner", "tokens", "block_tokens"])

    return schemas.select("element", "learner", _flat().alias("factors")).mapInPandas(run, "element string, learner string, tokens long, block_tokens double")


def order_disagreement(schemas: DataFrame, a: str = "exact", b: str = "dag") -> DataFrame:
    """(element, both, reversed, lost): pairs ordered by both schemas, in opposite ways, or by one only."""
    flat = schemas.select("element", "learner", F.explode(validate.flat(F.col("factors"))).alias("p")).select("element", "learner", "p.symbol", "p.factor", "p.place")
    left, right = (flat.select("element", "learner", F.col("symbol").alias(s), "factor", F.col("place").alias(p)) for s, p in (("x", "i"), ("y", "j")))
    ordered = left.join(right, ["element", "learner", "factor"]).where("i < j").select("element", "learner", "x", "y")
    keyed = ordered.select("element", "learner", F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v"), (F.col("x") < F.col("y")).alias("up"))
    of = lambda name: F.max(F.when(F.col("learner") == name, F.col("up")))
    pairs = keyed.groupBy("element", "u", "v").agg(of(a).alias("a"), of(b).alias("b"))
    return pairs.groupBy("element").agg(F.count_if(F.col("a") == F.col("b")).alias("both"), F.count_if(F.col("a") != F.col("b")).alias("reversed"), F.count_if(F.col("a").isNull() | F.col("b").isNull()).alias("lost"))


def perturbed(corpus: DataFrame) -> DataFrame:
    """A corpus of changed words, three for each: first two distinct neighbours swapped, last symbol doubled, first dropped."""
    s, n = F.col("symbols"), F.size("symbols")
    swapped = F.when(n > 1, F.concat(F.slice(s, 2, 1), F.slice(s, 1, 1), F.slice(s, F.lit(3), n))).otherwise(s)
    doubled = F.concat(s, F.slice(s, -1, 1))
    dropped = F.slice(s, F.lit(2), F.greatest(n, F.lit(1)))
    kinds = F.when(n > 0, F.array(*[F.struct(F.lit(k).alias("k"), w.alias("w")) for k, w in (("swap", swapped), ("double", doubled), ("drop", dropped))])).otherwise(F.array().cast("array<struct<k:string,w:array<string>>>"))
    return corpus.select("element", "word_id", F.explode(kinds).alias("c")).select("element", F.concat_ws("/", "word_id", "c.k").alias("word_id"), F.col("c.w").alias("symbols"))


def permissiveness(corpus: DataFrame, schemas: DataFrame) -> DataFrame:
    """(element, learner, words, accepted, share): changed words that each schema still accepts."""
    out = validate.coverage(perturbed(corpus), schemas)
    return out.withColumnRenamed("coverage", "share")


def set_ratio(graph_rows: DataFrame) -> DataFrame:
    """(element, symbols, exact_size, approx_size, ratio, bound): first independent sets; bound n / (log n)^2 without its constant."""

    def run(batches):
        import math

        import pandas as pd

        from ..plans.learn import _graphs
        from . import graphs

        for batch in batches:
            out = []
            for r in batch.itertuples(index=False):
                _, conflicts, _ = _graphs(r)
                g = graphs.within(conflicts, [v for v in conflicts if conflicts[v]])
                approx = len(graphs.auto_independent_set(g))
                try:
                    best = float(len(graphs.exact_independent_set(g)))
                except graphs.TooLarge:
                    best = math.nan
                n = len(g)
                out.append((r.element, n, best, approx, best / approx if approx else 1.0, n / math.log(n) ** 2 if n > 1 else 1.0))
            yield pd.DataFrame(out, columns=["element", "symbols", "exact_size", "approx_size", "ratio", "bound"])

    return graph_rows.mapInPandas(run, "element string, symbols long, exact_size double, approx_size long, ratio double, bound double")


def kernel_counters(corpus: DataFrame) -> DataFrame:
    """(element, words_read, edges, breaks, searches): work of the word-by-word graph, by reading order of word ids.

    Words are streamed through one graph per element, so no task holds more than a graph.
    """
    from ..plans.learn import dealt_words

    columns = ["element", "words_read", "edges", "breaks", "searches"]

    def run(batches):
        import pandas as pd

        from . import dag

        g, own, read = dag.PrecedenceGraph(), None, 0
        for batch in batches:
            done = []
            for w in batch.itertuples(index=False):
                if w.element != own:
                    if own is not None:
                        done.append((own, read, len(g.edges()), g.breaks, g.searches))
                    g, own, read = dag.PrecedenceGraph(), w.element, 0
                g.absorb(list(w.symbols))
                read += 1
            yield pd.DataFrame(done, columns=columns)
        if own is not None:
            yield pd.DataFrame([(own, read, len(g.edges()), g.breaks, g.searches)], columns=columns)

    return dealt_words(corpus, "first_seen").mapInPandas(run, "element string, words_read long, edges long, breaks long, searches long")
