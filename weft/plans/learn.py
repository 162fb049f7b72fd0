"""Learners: a corpus to one schema per element.

All data-sized work (profiles, signatures, pairs, counts) is relational and shared by the learners;
what reaches a kernel is one row per element with its alphabet, conflicts and stable order, whose
size depends on the alphabet alone.  Kernels run in ``mapInPandas`` over those rows, so no further
exchange is needed and nothing comes to the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import schema as S
from ..operators import batches, dag, graphs, precedence
from ..types import SCHEMA, assert_corpus

#: Parts that the tree-merged reading of an element's words is dealt to.
PARTS = 16

LEARNERS = ("is", "greedy", "exact", "exact_listed", "fewest")


def graph_rows(signed: DataFrame) -> DataFrame:
    """(element, words, symbols array<struct<symbol, mult>>, conflicts, stable) from signatures, one row per element.

    Signatures are read once: the word itself, its symbols and its pairs are exploded together, merged
    by one aggregate (unordered pairs with the directions seen) and gathered by element.
    """
    none, zero = F.lit(None).cast("string"), F.lit(0)
    item = lambda kind, x, y, c: F.struct(F.lit(kind).alias("kind"), x.alias("x"), y.alias("y"), c.cast("int").alias("c"))
    items = F.concat(
        F.array(item("word", none, none, zero)),
        F.transform("prof", lambda p: item("symbol", p["s"], none, p["c"])),
        F.transform(precedence.word_pairs(F.col("prof")), lambda p: item("pair", p["x"], p["y"], zero)),
    )
    each = signed.select("element", "n_words", F.explode(items).alias("i")).select("element", "n_words", "i.*")
    paired = F.col("kind") == "pair"
    u, v = F.when(paired, F.least("x", "y")).otherwise(F.col("x")), F.when(paired, F.greatest("x", "y"))
    seen = each.groupBy("element", "kind", u.alias("u"), v.alias("v")).agg(
        F.sum("n_words").alias("n"), F.min("c").alias("least"), F.max("c").alias("most"), F.bool_or(F.col("x") < F.col("y")).alias("up"), F.bool_or(F.col("x") > F.col("y")).alias("down")
    )
    return _gathered(seen)


def graph_rows_by_batches(corpus: DataFrame) -> DataFrame:
    """The same from a corpus nearly all of whose words differ: counts of batches are added up, words aren't merged first."""
    seen = batches.counts(corpus).groupBy("element", "kind", "u", "v").agg(
        F.sum("n").alias("n"), F.min("least").alias("least"), F.max("most").alias("most"), (F.sum("up") > 0).alias("up"), (F.sum("down") > 0).alias("down")
    )
    return _gathered(seen)


def relations(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """Graph rows of a corpus by a plan of ``precedence.pairs``: ``profile`` or ``batches``."""
    if plan == "batches":
        return graph_rows_by_batches(corpus)
    if plan != "profile":
        raise ValueError(f"no such plan: {plan}")
    return graph_rows(precedence.signatures(precedence.profile(corpus)))


def _gathered(seen: DataFrame) -> DataFrame:
    """One row per element from its counted words, symbols and pairs."""
    of = lambda condition, *columns: F.array_sort(F.collect_list(F.when(condition, F.struct(*columns))))
    up, both = F.col("up"), F.col("up") & F.col("down")
    first, second = F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y")
    gathered = seen.groupBy("element").agg(
        F.max(F.when(F.col("kind") == "word", F.col("n"))).alias("words"),
        of(F.col("kind") == "symbol", F.col("u").alias("symbol"), "n", "least", "most").alias("counts"),
        of((F.col("kind") == "pair") & both, first, second).alias("conflicts"),
        of((F.col("kind") == "pair") & ~both, first, second).alias("stable"),
    )
    mult = lambda c: precedence.mult(F.when(c["n"] < F.col("words"), 0).otherwise(c["least"]), c["most"])
    symbols = F.transform("counts", lambda c: F.struct(c["symbol"].alias("symbol"), mult(c).alias("mult")))
    return gathered.select("element", "words", symbols.alias("symbols"), "conflicts", "stable")


def _graphs(row) -> tuple[dict[str, str], graphs.Graph, dict[str, set[str]]]:
    mult = {s["symbol"]: s["mult"] for s in row.symbols}
    conflicts = graphs.graph(mult, [(p["x"], p["y"]) for p in row.conflicts])
    after: dict[str, set[str]] = {s: set() for s in mult}
    for p in row.stable:
        after[p["x"]].add(p["y"])
    return mult, conflicts, after


def _partition(learner: str, conflicts: graphs.Graph) -> tuple[list[list[str]], str]:
    """Sets of symbols without conflicts, and a status.

    ``ok``; ``too_large``: the search was given up and the approximate answer stands; ``greedy``: beyond
    the size for clique exclusion, the greedy sets stand.
    """
    auto = "ok" if sum(map(bool, conflicts.values())) <= graphs.MAX_CLIQUE_EXCLUSION else "greedy"
    try:
        if learner == "exact":
            return graphs.iterate_sets(conflicts, graphs.exact_independent_set), "ok"
        if learner == "exact_listed":
            return graphs.iterate_sets(conflicts, lambda g: graphs.largest_by_enumeration(g, graphs.MAX_WORK)), "ok"
        if learner == "fewest":
            return graphs.fewest_sets(conflicts), "ok"
    except graphs.TooLarge:
        return graphs.iterate_sets(conflicts, graphs.auto_independent_set), "too_large"
    if learner == "greedy":
        return graphs.iterate_sets(conflicts, graphs.greedy_independent_set), "ok"
    return graphs.iterate_sets(conflicts, graphs.auto_independent_set), auto


def _finished(row, learner: str, chains: list[list[str]], mult: dict[str, str], status: str, repaired: bool) -> tuple:
    factors = S.canonical([[(s, mult[s]) for s in chain] for chain in chains])
    return (row.element, learner, [[{"symbol": s, "mult": m} for s, m in f] for f in factors], int(row.words), status, repaired, S.to_text(factors))


_COLUMNS = ["element", "learner", "factors", "words", "status", "repaired", "text"]


def from_graph_rows(rows: DataFrame, learners: tuple[str, ...]) -> DataFrame:
    """Schema rows of every learner named, from one pass over the graph rows."""

    def run(frames):
        import pandas as pd

        for batch in frames:
            out = []
            for row in batch.itertuples(index=False):
                mult, conflicts, after = _graphs(row)
                for learner in learners:
                    sets, status = _partition(learner, conflicts)
                    parts = [(s, graphs.cycle_repair(s, after)) for s in sets]
                    chains = [graphs.topological(p, after) for _, ps in parts for p in ps]
                    out.append(_finished(row, learner, chains, mult, status, any(len(ps) > 1 for _, ps in parts)))
            yield pd.DataFrame(out, columns=_COLUMNS)

    return rows.mapInPandas(run, SCHEMA)


def by_independent_sets(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """Approximate learner: repeated independent sets of the conflict graph, found by excluding cliques."""
    return learn(corpus, ("is",), plan)


def exact(corpus: DataFrame, objective: str = "iterated", plan: str = "profile") -> DataFrame:
    """Exact learner: repeated maximum sets (``iterated``), or as few sets as possible (``fewest``).

    Beyond the work of the search (``fewest``: its cap), the row has status ``too_large`` and the approximate answer.
    """
    return learn(corpus, ({"iterated": "exact", "fewest": "fewest"}[objective],), plan)


def learn(corpus: DataFrame, learners: tuple[str, ...] = ("is", "exact"), plan: str = "profile") -> DataFrame:
    """Schemas of a corpus by the learners named; a null element, word or symbol fails the job."""
    return from_graph_rows(relations(assert_corpus(corpus), plan), learners)


def learn_rows(long_rows: DataFrame, learners: tuple[str, ...] = ("is", "exact")) -> DataFrame:
    """The same from long rows (element, word_id, position, symbol), words never being materialised."""
    return from_graph_rows(graph_rows(precedence.signatures(precedence.profile_from_rows(long_rows))), learners)


def collapsed(corpus: DataFrame, plan: str = "profile") -> DataFrame:
    """(element, symbols, first, n_words): distinct words with runs of a symbol made one.

    ``first`` is the least word_id, shorter ids first, so that numbers count up.
    """
    if plan == "batches":
        short = batches.collapsed(corpus)
    else:
        symbols = F.col("symbols")
        short = corpus.select("element", "word_id", F.filter(symbols, lambda s, i: (i == 0) | (s != F.get(symbols, i - 1))).alias("symbols"))
    return short.groupBy("element", "symbols").agg(F.min(F.struct(F.length("word_id"), "word_id"))["word_id"].alias("first"), F.count("*").alias("n_words"))


def _order(order: str):
    keys = {"first_seen": lambda w: (len(w["first"]), w["first"], list(w["symbols"])), "lex": lambda w: list(w["symbols"]), "freq": lambda w: (-w["n_words"], list(w["symbols"]))}
    return keys[order]


def dealt_words(corpus: DataFrame, order: str, parts: int = 1, plan: str = "profile") -> DataFrame:
    """(element, symbols, first, n_words, part): distinct run-collapsed words, those of an element and part together and in reading order."""
    dealt = collapsed(corpus, plan).withColumn("part", F.pmod(F.xxhash64("symbols"), F.lit(parts)))
    ranks = {"first_seen": [F.length("first"), F.col("first")], "lex": [], "freq": [F.desc("n_words")]}[order]
    return dealt.repartition("element", "part").sortWithinPartitions("element", "part", *ranks, "symbols")


def by_precedence_dag(corpus: DataFrame, order: str = "first_seen", merge: str = "none", parts: int = PARTS, plan: str = "profile") -> DataFrame:
    """Heuristic learner: a precedence graph built from neighbouring symbols, word by word.

    Only distinct run-collapsed words are read, in a fixed order: by word_id (shorter ids first, so
    numbers count up), lexicographically, or by falling frequency.  They are streamed in that order and
    those that change the graph are kept; the kernel then reads the kept words alone, so no task holds
    more than a graph and those.  ``merge='none'`` streams all words of an element through one graph,
    as the method has it: a word that leaves it as it is can be left out.  ``merge='tree'`` (learner
    ``dag_tree``) deals them to ``parts`` with a graph each, whose kept words need not give that graph.
    Status ``paths_capped``: the finished graph has too many paths, its connected parts stand for them.
    """
    corpus = assert_corpus(corpus)
    key = _order(order)
    if merge not in ("none", "tree"):
        raise ValueError(f"no such merge: {merge}")

    def keep(frames):
        import pyarrow as pa

        g, own = dag.PrecedenceGraph(), None
        for batch in frames:
            element, part = batch.column("element").to_pylist(), batch.column("part").to_pylist()
            held, start = [], 0
            while start < len(element):
                if (element[start], part[start]) != own:
                    g, own = dag.PrecedenceGraph(), (element[start], part[start])
                end = start + 1
                while end < len(element) and (element[end], part[end]) == own:
                    end += 1
                held += [start + i for i in g.absorb_all(batch.column("symbols").slice(start, end - start))]
                start = end
            yield batch.select(["element", "symbols", "first", "n_words"]).take(pa.array(held, pa.int64()))

    dealt = dealt_words(corpus, order, parts if merge == "tree" else 1, plan)
    words = dealt.select("element", "symbols", "first", "n_words", "part").mapInArrow(keep, "element string, symbols array<string>, first string, n_words long")
    listed = words.groupBy("element").agg(F.collect_list(F.struct("symbols", "first", "n_words")).alias("read"))
    rows = relations(corpus, plan).join(listed, "element")

    def run(frames):
        import pandas as pd

        for batch in frames:
            out = []
            for row in batch.itertuples(index=False):
                mult, conflicts, after = _graphs(row)
                g = dag.PrecedenceGraph(mult)
                for w in sorted(row.read, key=key):
                    g.absorb(list(w["symbols"]))
                chains, repaired = dag.chains(g, conflicts, after)
                out.append(_finished(row, "dag" if merge == "none" else "dag_tree", chains, mult, "paths_capped" if g.capped else "ok", repaired))
            yield pd.DataFrame(out, columns=_COLUMNS)

    return rows.mapInPandas(run, SCHEMA)


def compare_learners(corpus: DataFrame, merge: str = "none", plan: str = "profile") -> DataFrame:
    """Exact, approximate and heuristic schemas of every element."""
    return learn(corpus, ("exact", "is"), plan).unionByName(by_precedence_dag(corpus, merge=merge, plan=plan))
