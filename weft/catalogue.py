"""Catalogue of the engine's named queries and the SQL each is checked against."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles, workloads
from .functions import schema as S
from .operators import baselines, extensions, measures, precedence, validate
from .plans import learn
from .sources import generate
from .sources.tables import shared_folder, table
from .streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]

#: Workloads whose relations are queried one by one, and those that only learners and measures run on.
RELATIONAL = (
    "pages", "conversations", "events", "users", "customers", "segments", "lineitem", "brands", "dims", "documents", "languages", "qualities", "toxicities", "props", "part_brands", "sessions",
    "planted",
)
LEARNED = (*RELATIONAL, "page_children")
#: Workloads with many distinct words under one element, on which the two-round variant of the graph runs too.
TWO_ROUNDS = ("lineitem", "events", "segments", "brands", "planted")
#: Plan of the relations, for workloads nearly all of whose words differ.
PLAN = {"planted": "batches"}


def _words(words: DataFrame) -> DataFrame:
    return words.select("element", "word_id", F.array_join("symbols", " ").alias("symbols"))


def _partition(schemas: DataFrame) -> DataFrame:
    sets = schemas.select("element", F.explode(F.transform("factors", lambda f: F.array_sort(F.transform(f, lambda p: p["symbol"])))).alias("s"))
    return sets.select("element", F.array_join("s", " ").alias("symbols"))


def _text(schemas: DataFrame) -> DataFrame:
    return schemas.select("element", "learner", "words", "status", "repaired", "text")


def _conflict_graph(w: DataFrame, plan: str) -> DataFrame:
    edges = precedence.conflict_graph(precedence.pairs(w, plan))
    return edges.select("element", F.array_join(F.transform("edges", lambda e: F.concat(e["x"], F.lit("-"), e["y"])), " ").alias("edges"))


def _star_relation(w: DataFrame) -> DataFrame:
    return measures.compare(learn.by_independent_sets(w), baselines.star_schema_rows(w)).select("element", "relation")


def _chain(w: DataFrame) -> DataFrame:
    return baselines.ordered_chain(w).select("element", "text")


def _chain_coverage(w: DataFrame) -> DataFrame:
    return baselines.chain_accepts(w, baselines.ordered_chain(w)).groupBy("element").agg(F.count("*").alias("words"), F.count_if("accepted").alias("accepted"))


def _on(name: str, plan: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, d: plan(workloads.BUILDERS[name](spark, d))


def _per_workload() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for n in RELATIONAL:
        plan = PLAN.get(n, "profile")
        out |= {
            f"words_{n}": _on(n, _words),
            f"precedence_{n}": _on(n, lambda w, plan=plan: precedence.pairs(w, plan)),
            f"conflict_graph_{n}": _on(n, lambda w, plan=plan: _conflict_graph(w, plan)),
            f"conflicts_{n}": _on(n, lambda w, plan=plan: precedence.conflicts(precedence.pairs(w, plan))),
            f"stable_{n}": _on(n, lambda w, plan=plan: precedence.stable(precedence.pairs(w, plan))),
            f"multiplicities_{n}": _on(n, lambda w, plan=plan: precedence.multiplicities(w, plan)),
            f"conflict_density_{n}": _on(n, lambda w, plan=plan: measures.conflict_density(w, plan)),
            f"multiplicity_only_{n}": _on(n, lambda w, plan=plan: baselines.multiplicities_only(w, plan).select("element", "words", "text")),
        }
    for n in ("pages", "conversations", "events", "lineitem", "users"):
        out |= {
            f"sample_sizes_{n}": _on(n, lambda w: measures.sample_sizes(w).drop("signatures")),
            f"star_{n}": _on(n, lambda w: baselines.star(w).select("element", "words", "text")),
            f"adjacency_{n}": _on(n, precedence.adjacency),
        }
    for n in ("pages", "conversations", "events", "users", "customers", "segments", "lineitem", "brands", "planted"):
        plan = PLAN.get(n, "profile")
        out |= {
            f"partition_exact_{n}": _on(n, lambda w, plan=plan: _partition(learn.exact(w, plan=plan))),
            f"interleavings_exact_{n}": _on(n, lambda w, plan=plan: measures.interleavings(learn.exact(w, plan=plan)).select("element", "interleavings")),
            f"simplified_exact_{n}": _on(n, lambda w, plan=plan: measures.simplified(learn.exact(w, plan=plan)).select("element", "sizes")),
        }
    for n in LEARNED:
        plan = PLAN.get(n, "profile")
        out |= {
            f"schema_is_{n}": _on(n, lambda w, plan=plan: _text(learn.by_independent_sets(w, plan))),
            f"schema_exact_{n}": _on(n, lambda w, plan=plan: _text(learn.exact(w, plan=plan))),
        }
        if n not in ("languages", "toxicities", "sessions", "part_brands"):  # other cuts of documents, events and brands
            out[f"schema_dag_{n}"] = _on(n, lambda w, plan=plan: _text(learn.by_precedence_dag(w, plan=plan)))
        if n in TWO_ROUNDS:
            out[f"schema_dag_tree_{n}"] = _on(n, lambda w, plan=plan: _text(learn.by_precedence_dag(w, merge="tree", plan=plan)))
    for n in ("pages", "conversations", "events", "lineitem", "users"):
        out |= {
            f"coverage_{n}": _on(n, lambda w: validate.coverage(w, learn.compare_learners(w))),
            f"chain_{n}": _on(n, _chain),
            f"chain_coverage_{n}": _on(n, _chain_coverage),
            f"compare_star_{n}": _on(n, _star_relation),
            f"together_{n}": _on(n, baselines.together),
            f"disjunctive_{n}": _on(n, lambda w: baselines.disjunctive_multiplicities(w).select("element", "text")),
            f"exclusive_pairs_{n}": _on(n, extensions.exclusive_pairs),
        }
    for n in ("pages", "conversations", "events", "lineitem", "users", "planted"):
        plan = PLAN.get(n, "profile")
        out[f"compare_chain_{n}"] = _on(n, lambda w, plan=plan: measures.compare_chain(learn.exact(w, plan=plan), baselines.ordered_chain(w, plan)))
    for n in ("users", "customers"):
        out[f"choices_{n}"] = _on(n, lambda w: extensions.choices_in_factors(w, learn.exact(w)))
    for n in ("users", "dims"):
        out[f"global_order_{n}"] = _on(n, baselines.global_order)
    for n in ("pages", "users", "planted"):
        plan = PLAN.get(n, "profile")
        out |= {
            f"compare_chain_all_{n}": _on(n, lambda w, plan=plan: measures.compare_chain(learn.compare_learners(w, plan=plan), baselines.ordered_chain(w, plan))),
            f"learner_table_{n}": _on(n, lambda w, plan=plan: measures.learner_table(learn.compare_learners(w, plan=plan))),
            f"gap_{n}": _on(n, lambda w, plan=plan: measures.gap(learn.learn(w, ("exact", "is"), plan))),
            f"gap_dag_{n}": _on(n, lambda w, plan=plan: measures.gap(learn.exact(w, plan=plan).unionByName(learn.by_precedence_dag(w, plan=plan)))),
            f"order_disagreement_{n}": _on(n, lambda w, plan=plan: measures.order_disagreement(learn.compare_learners(w, plan=plan))),
            f"minimality_{n}": _on(n, lambda w, plan=plan: measures.minimality(learn.compare_learners(w, plan=plan), learn.relations(w, plan))),
        }
    return out


# --- single queries -------------------------------------------------------------------------------


def precedence_selfjoin(spark, d):
    return precedence.pairs(workloads.events(spark, d), "selfjoin")


def precedence_positions(spark, d):
    return precedence.pairs(workloads.conversations(spark, d), "positions")


def precedence_from_rows(spark, d):
    """Pairs straight from rows, words never materialised."""
    return precedence.pairs_of(precedence.signatures(precedence.profile_from_rows(workloads.lineitem_rows(spark, d))))


def schema_exact_from_rows(spark, d):
    return _text(learn.learn_rows(workloads.lineitem_rows(spark, d), ("exact",)))


def schema_fewest_users(spark, d):
    return _text(learn.exact(workloads.users(spark, d), "fewest"))


def schema_listed_pages(spark, d):
    return _text(learn.learn(workloads.pages(spark, d), ("exact_listed",)))


def schema_greedy_dims(spark, d):
    return _text(learn.learn(workloads.dims(spark, d), ("greedy",)))


def schema_dag_orders(spark, d):
    """The word-by-word learner under three reading orders."""
    w = workloads.conversations(spark, d)
    rows = [learn.by_precedence_dag(w, order).withColumn("reading", F.lit(order)) for order in ("first_seen", "lex", "freq")]
    return rows[0].union(rows[1]).union(rows[2]).select("element", "reading", "text")


def schema_dag_tree(spark, d):
    return _text(learn.by_precedence_dag(workloads.users(spark, d), merge="tree"))


def examples(spark, d):
    """All learners on the events' days and the segments' customers, side by side."""
    w = workloads.events(spark, d).unionByName(workloads.segments(spark, d))
    return _text(learn.compare_learners(w)).union(_text(learn.learn(w, ("greedy", "fewest", "exact_listed"))))


def _planted_sets() -> list[tuple[str, list[str]]]:
    return [(n, sorted(" ".join(sorted(s + m for s, m in f)) for f in v)) for n, v in generate.parsed().items()]


def _recovery(spark, schemas: DataFrame) -> DataFrame:
    """Whether schemas are the planted layouts again, up to the order that words leave open."""
    learned = schemas.select("element", "learner", "text", F.array_sort(F.transform("factors", lambda f: F.array_join(F.array_sort(F.transform(f, lambda p: F.concat(p["symbol"], p["mult"]))), " "))).alias("sets"))
    truth = spark.createDataFrame(_planted_sets(), "element string, planted array<string>")
    return learned.join(F.broadcast(truth), "element").select("element", "learner", (F.col("sets") == F.col("planted")).alias("recovered"), "text")


def planted_recovery(spark, d):
    """The set-based learners on the planted layouts."""
    return _recovery(spark, learn.learn(workloads.planted(spark, d), ("exact", "is"), PLAN["planted"]))


def planted_recovery_dag(spark, d):
    """The word-by-word learner on the planted layouts, in two reading orders."""
    w = workloads.planted(spark, d)
    read = [learn.by_precedence_dag(w, order, plan=PLAN["planted"]).withColumn("learner", F.lit(f"dag {order}")) for order in ("first_seen", "lex")]
    return _recovery(spark, read[0].union(read[1]))


def membership_benchmark(spark, d):
    """Benchmark items under the schema of the documents."""
    return validate.accepts(workloads.benchmark(spark, d), learn.exact(workloads.documents(spark, d)))


def membership_holdout(spark, d):
    """Schemas learned from half of the customers' years, tried on the other half; customers without a schema are counted, too."""
    w = workloads.customers(spark, d).withColumn("learned", F.md5(F.col("word_id").cast("binary")) < "8")
    found = validate.accepts(w.where("not learned").drop("learned"), learn.exact(w.where("learned").drop("learned")))
    return found.groupBy("learner", "reason").agg(F.count("*").alias("words"))


def contrast_qualities(spark, d):
    """Language relation of the schemas of good and of bad documents."""
    s = learn.exact(workloads.qualities(spark, d))
    a = s.where("element = 'quality 1'").withColumn("element", F.lit("quality"))
    b = s.where("element = 'quality 0'").withColumn("element", F.lit("quality"))
    return measures.compare(a, b)


def permissiveness_users(spark, d):
    w = workloads.users(spark, d)
    return measures.permissiveness(w, learn.exact(w).unionByName(baselines.star_schema_rows(w)))


def orders_accepted_planted(spark, d):
    """Orders that the schemas learned from the planted words accept."""
    learned = learn.exact(workloads.planted(spark, d), plan=PLAN["planted"])
    return measures.log_orders(learned).select("element", "log_orders", "orders")


def count_schemas(spark, d):
    """Schemas over as many symbols as some word of the events has."""
    n = workloads.events(spark, d).select(F.size(F.array_distinct("symbols")).cast("long").alias("n")).where("n > 0").distinct()
    each = n.select("n", F.explode(F.sequence(F.lit(1).cast("long"), "n")).alias("k"))
    choose = lambda a, b: F.factorial(a.cast("int")) / (F.factorial(b.cast("int")) * F.factorial((a - b).cast("int")))
    term = F.factorial(F.col("n").cast("int")) / F.factorial(F.col("k").cast("int")) * choose(F.col("n") - 1, F.col("k") - 1)
    exact = each.groupBy("n").agg(F.sum(term).cast("long").alias("schemas"))
    bell, asymptotic = F.udf(lambda i: S.count_schemas(i, "ordered_bell"), "long"), F.udf(lambda i: float(S.count_schemas(i, "asymptotic")), "double")  # a row for each size
    return exact.select("n", "schemas", bell("n").alias("ordered_bell"), F.round(asymptotic("n"), 3).alias("asymptotic"))


def length_users(spark, d):
    return measures.length(learn.exact(workloads.users(spark, d)))


def set_ratio_dims(spark, d):
    return measures.set_ratio(learn.graph_rows(precedence.signatures(precedence.profile(workloads.dims(spark, d)))))


def kernel_counters_users(spark, d):
    return measures.kernel_counters(workloads.users(spark, d))


def frequent_precedence_pages(spark, d):
    return extensions.frequent_precedence(workloads.pages(spark, d), 0.9)


def closed_precedence_pages(spark, d):
    return extensions.closed_precedence(extensions.frequent_precedence(workloads.pages(spark, d), 0.5))


def frequent_by_projection(spark, d):
    """The library's sequence mining on the conversations: the pairs of frequent_precedence again."""
    return extensions.frequent_by_projection(workloads.conversations(spark, d), "conversation", 0.5)


def membership_general(spark, d):
    """Words of the events under a schema that uses a symbol twice."""
    schema = S.parse("click view & click", single=False)
    accepted = F.udf(lambda w: S.accepts_general(schema, w), "boolean")
    return workloads.events(spark, d).select("word_id", F.array_join("symbols", " ").alias("word"), accepted("symbols").alias("accepted"))


def sessions_stream(spark, d):
    """Schemas of users learned from a stream of their events; sessions still open at the end of the stream don't count yet."""
    events = spark.read.parquet(f"{d}/events.parquet")
    stream = spark.readStream.schema(events.schema).parquet(f"{d}/events.parquet*")
    return _text(incremental.learn_stream(incremental.session_words(stream), f"{shared_folder(spark)}/weft-stream-{uuid.uuid4().hex}"))


def fold_batches(spark, d):
    """Schemas of users from a state folded of three batches, one of them delivered twice."""
    w = workloads.users(spark, d).withColumn("b", F.pmod(F.xxhash64("word_id"), F.lit(3)))
    state = None
    for b in (2, 0, 1, 0):
        state = incremental.fold(state, incremental.batch_state(w.where(F.col("b") == b).drop("b"), b))
    return _text(incremental.schemas(state, ("exact",)))


def saturated_events(spark, d):
    return incremental.saturated(incremental.batch_state(workloads.events(spark, d)))


def _of_texts(spark, schemas: DataFrame, call: str) -> DataFrame:
    """(text, found): a table function's rows for each distinct schema, worked out once for all elements that have it."""
    from .functions import sql

    sql.register_all(spark)
    texts = schemas.select("text").distinct()
    return spark.sql(f"SELECT text, array_join(f.*, ' ') AS found FROM {{texts}}, LATERAL {call} f", texts=texts)


def enumerate_language(spark, d):
    """Words of up to three symbols in the languages of the users' schemas."""
    return _of_texts(spark, learn.exact(workloads.users(spark, d)), "enumerate_language(text, 3)").withColumnRenamed("found", "word")


def block_orders(spark, d):
    """Orders of the symbols, each with its repeats as one block, that the users' schemas accept."""
    return _of_texts(spark, learn.exact(workloads.users(spark, d)), "block_orders(text)").withColumnRenamed("found", "blocks")


def shuffle_words(spark, d):
    """Merges of what users looked at on a day with what else they did, for each two such words that occur together."""
    from .functions import sql

    sql.register_all(spark)
    part = lambda c: F.filter("symbols", lambda s: s.isin("click", "view") == c)
    both = workloads.events(spark, d).select(part(True).alias("u"), part(False).alias("v")).distinct()
    return spark.sql("SELECT array_join(u, ' ') AS u, array_join(v, ' ') AS v, array_join(word, ' ') AS word FROM {both}, LATERAL shuffle_words(u, v, 100000)", both=both)


def hardness_witness(spark, d):
    """Conflicts of the corpus made from the conflict graph of the events: the graph again."""
    v = table(spark, d, "events", "event_type").where("event_type is not null").select(F.col("event_type").alias("v")).distinct()
    e = precedence.directed(precedence.pairs(workloads.events(spark, d))).where("conflict").select("x", "y")
    return precedence.conflicts(precedence.pairs(generate.words_from_graph(v, e)))


def learn_aggregate(spark, d):
    """Schemas by the aggregate function, one small group per user."""
    from .functions import sql

    sql.register_all(spark)
    workloads.users(spark, d).createOrReplaceTempView("weft_user_words")
    return spark.sql("SELECT element, learn_schema(symbols) AS text FROM weft_user_words GROUP BY element")


def sessions_batch(spark, d):
    """Words of the sessions of a finished event table, as the stream gives them."""
    return _words(workloads.sessions(spark, d))


# --- surrounding operators -----------------------------------------------------------------------


def density_cube(spark, d):
    """Events by type and hour, with subtotals."""
    rows = table(spark, d, "events", "event_type", "ts").select("event_type", F.hour("ts").alias("hour"))
    return rows.cube("event_type", "hour").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def orders_rollup(spark, d):
    rows = table(spark, d, "orders", "o_orderpriority", "o_orderstatus", "o_totalprice")
    return rows.rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.max("o_totalprice"), 2).alias("most"))


def roles_pivot(spark, d):
    rows = table(spark, d, "conversations", "conv_id", "role")
    return rows.groupBy("conv_id").pivot("role", ["assistant", "system", "user"]).count().na.fill(0)


def as_of_orders(spark, d):
    """For each order the date of the customer's order before it."""
    rows = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    before = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, -1)
    return rows.select("o_orderkey", F.last("o_orderdate", ignorenulls=True).over(before).cast("date").cast("string").alias("previous"))


def range_pairs(spark, d):
    """Purchases with the number of clicks of the same user in the hour before, by hour buckets."""
    rows = table(spark, d, "events", "event_id", "ts", "user_id", "event_type").select("event_id", "user_id", "event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t"))
    late = rows.where("event_type = 'purchase'").select("event_id", "user_id", F.col("t").alias("t1"), F.explode(F.array(F.floor(F.col("t") / 3600), F.floor(F.col("t") / 3600) - 1)).alias("b"))
    early = rows.where("event_type = 'click'").select("user_id", F.col("t").alias("t0"), F.floor(F.col("t") / 3600).alias("b"))
    near = late.join(early, ["user_id", "b"]).where("t0 <= t1 and t0 > t1 - 3600")
    return near.groupBy("event_id").agg(F.count("*").alias("clicks"))


def frequent_words(spark, d):
    """The ten most frequent words of each user."""
    w = workloads.users(spark, d).groupBy("element", F.array_join("symbols", " ").alias("word")).agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("element").orderBy(F.desc("n"), "word"))
    return w.withColumn("place", rank.cast("long")).where("place <= 10")


def longest_runs(spark, d):
    """Longest run of one event type for each user, by gaps and islands."""
    by_user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = table(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    step = rows.withColumn("new", (F.coalesce(F.lag("event_type").over(by_user), F.lit("")) != F.col("event_type")).cast("long"))
    islands = step.withColumn("island", F.sum("new").over(by_user.rowsBetween(Window.unboundedPreceding, 0)))
    return islands.groupBy("user_id", "island").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.max("n").alias("longest"))


def unknown_words(spark, d):
    """Words with a symbol that no other word has."""
    flat = workloads.pages(spark, d).select("word_id", F.explode(F.array_distinct("symbols")).alias("s"))
    known = flat.groupBy("s").agg(F.count("*").alias("n")).where("n > 1")
    return flat.join(known, "s", "left_anti").select("word_id", F.col("s").alias("symbol"))


SINGLE: dict[str, Query] = {
    f.__name__: f
    for f in (
        precedence_selfjoin, precedence_positions, precedence_from_rows, schema_exact_from_rows, schema_fewest_users, schema_listed_pages, schema_greedy_dims,
        schema_dag_orders, schema_dag_tree, examples, planted_recovery, planted_recovery_dag, membership_benchmark, membership_holdout, contrast_qualities, permissiveness_users,
        orders_accepted_planted, count_schemas, length_users, set_ratio_dims, kernel_counters_users,
        frequent_precedence_pages, closed_precedence_pages, frequent_by_projection, membership_general, sessions_stream, fold_batches, saturated_events, enumerate_language, block_orders, shuffle_words, hardness_witness,
        learn_aggregate, sessions_batch, density_cube, orders_rollup, roles_pivot, as_of_orders, range_pairs, frequent_words, longest_runs, unknown_words,
    )
}


def queries() -> dict[str, Query]:
    return _per_workload() | SINGLE


# --- SQL ------------------------------------------------------------------------------------------


def _sql(name: str, kind: str) -> str:
    return oracles.over(workloads.SQL[name], oracles.SELECT.get(kind, kind), large=name in oracles.LARGE, excluded=kind == "schema_is" and name != "planted")


def _schema(name: str, learner: str) -> str:
    return _sql(name, "schema_exact").replace("'exact' AS learner", f"'{learner}' AS learner")


def _gap(name: str) -> str:
    """Sizes of the two set-based learners side by side, each by its own SQL."""
    sizes = "SELECT total.element, coalesce(list(n ORDER BY n DESC) FILTER (n IS NOT NULL), []) AS z FROM total LEFT JOIN factors USING (element) GROUP BY total.element"
    a, b = (oracles.over(workloads.SQL[name], sizes, large=name in oracles.LARGE, excluded=x) for x in (False, True))
    differs = "list_filter(list_transform(range(1, greatest(len(a.z), len(b.z)) + 1), lambda i: coalesce(a.z[i], 0) - coalesce(b.z[i], 0)), lambda d: d <> 0)"
    return f"SELECT a.element, 'is' AS learner, (len(b.z) - len(a.z))::BIGINT AS more_factors, coalesce({differs}[1], 0)::BIGINT AS first_difference FROM ({a}) a JOIN ({b}) b ON a.element = b.element"


def _judged(words: str, u: str, select: str) -> str:
    return oracles.over(words, select, u=f"u AS ({u})")


#: Workloads whose exact schemas SQL can work out, and those of them on which each other learner is known to find the same
#: schemas (their conflict graphs leave no choice).
EXACT = ("pages", "conversations", "events", "users", "customers", "segments", "lineitem", "brands", "props", "documents", "languages", "qualities", "toxicities", "sessions", "planted")
AGREEING = {
    "is": ("planted",),  # too many symbols in conflict for the SQL of that learner
    "dag": ("events", "segments", "lineitem", "brands", "props"),
    "dag_tree": ("events", "segments", "lineitem", "brands"),
}


def oracle_sql() -> dict[str, str]:
    known = _per_workload()
    out = {}
    for name in workloads.SQL:
        for kind in oracles.SELECT:
            if f"{kind}_{name}" in known and (name in EXACT or "exact" not in kind and kind not in ("schema_is", "compare_chain", "length", "coverage")):
                out[f"{kind}_{name}"] = _sql(name, kind)
        for learner, names in AGREEING.items():
            query = f"schema_{learner}_{name}"
            if query in known and name in names:
                out[query] = _schema(name, learner)
    del out["compare_star_users"]  # a user with one symbol has the star's own language
    planted = ", ".join(f"('{n}', {v})" for n, v in _planted_sets())
    half = lambda n: f"SELECT element, word_id, symbols FROM ({workloads.SQL['customers']}) WHERE (md5(word_id) < '8') = {n}"
    return out | {
        "schema_exact_from_rows": _schema("lineitem", "exact"),
        "fold_batches": _schema("users", "exact"),
        "schema_listed_pages": _schema("pages", "exact_listed"),
        "planted_recovery": _sql(
            "planted",
            "SELECT t.element, learner, found = layout AS recovered, text FROM texts t JOIN (SELECT element, list(x ORDER BY x) AS found FROM (SELECT element, string_agg(s || mult, ' ' ORDER BY s || mult) AS x FROM placed GROUP BY element, no, sub) GROUP BY element) f ON f.element = t.element "
            f"JOIN (VALUES {planted}) v(element, layout) ON v.element = t.element, (VALUES ('exact'), ('is')) l(learner)",
        ),
        **{f"gap_{n}": _gap(n) for n in ("pages", "users")},
        "length_users": _sql("users", "length"),
        "membership_benchmark": _judged(workloads.SQL["documents"], workloads.SQL["benchmark"], "SELECT element, word_id, 'exact' AS learner, reason = 'ok' AS accepted, reason FROM verdict"),
        "membership_holdout": _judged(half("true"), half("false"), "SELECT CASE WHEN reason <> 'no_schema' THEN 'exact' END AS learner, reason, count(*) AS words FROM verdict GROUP BY ALL"),
        "permissiveness_users": oracles.over(workloads.SQL["users"], "SELECT element, learner, count(*) AS words, count(*) FILTER (WHERE learner = 'star' OR reason = 'ok') AS accepted, round(accepted / words, 6) AS share FROM verdict, (VALUES ('exact'), ('star')) l(learner) GROUP BY element, learner", u=oracles.PERTURBED),
        "closed_precedence_pages": _sql("pages", "SELECT element, x, y, support FROM (SELECT element, x, y, round(n_words / words, 6) AS support FROM pairs JOIN total USING (element)) f WHERE support >= 0.5 AND NOT EXISTS (SELECT 1 FROM (SELECT element, x, y, round(n_words / words, 6) AS support FROM pairs JOIN total USING (element)) a JOIN (SELECT element, x, y, round(n_words / words, 6) AS support FROM pairs JOIN total USING (element)) b ON a.element = b.element AND a.y = b.x WHERE a.element = f.element AND a.x = f.x AND b.y = f.y AND a.support >= f.support AND b.support >= f.support)"),
        "sessions_batch": _sql("sessions", "words"),
        "examples": " UNION ALL ".join(f"SELECT * FROM ({_schema(name, learner)})" for name in ("events", "segments") for learner in ("exact", "is", "dag", "greedy", "fewest", "exact_listed")),
        "enumerate_language": oracles.over(workloads.SQL["users"], "SELECT DISTINCT text, word_id AS word FROM verdict JOIN texts USING (element) WHERE reason = 'ok'", u=oracles.UP_TO_THREE),
        "block_orders": oracles.over(workloads.SQL["users"], "SELECT DISTINCT text, word_id AS blocks FROM verdict JOIN u USING (element, word_id) JOIN texts USING (element) JOIN (SELECT element, count(*) AS n FROM counts GROUP BY element) USING (element) WHERE reason = 'ok' AND len(u.symbols) = n", u=oracles.PERMUTED),
        "precedence_selfjoin": _sql("events", "precedence"),
        "precedence_positions": _sql("conversations", "precedence"),
        "precedence_from_rows": _sql("lineitem", "precedence"),
        "frequent_precedence_pages": _sql("pages", "SELECT element, x, y, round(n_words / words, 6) AS support FROM pairs JOIN total USING (element) WHERE round(n_words / words, 6) >= 0.9"),
        "frequent_by_projection": _sql("conversations", "SELECT element, x, y, round(n_words / words, 6) AS support FROM pairs JOIN total USING (element) WHERE n_words >= 0.5 * words"),
        "membership_general": _sql("events", "SELECT word_id, word, word IN ('click click view', 'click view click') AS accepted FROM (SELECT word_id, array_to_string(symbols, ' ') AS word FROM w)"),
        "saturated_events": _sql("events", f"SELECT element, (SELECT count(*) FROM pairs q WHERE q.element = c.element AND {oracles.REVERSE}) = count(*) * (count(*) - 1) AND bool_and(mult = '*') AS saturated FROM mults c GROUP BY element"),
        "count_schemas": f"WITH t AS (SELECT n, sum((factorial(n::INT) / factorial(k::INT)) * (factorial((n - 1)::INT) / (factorial((k - 1)::INT) * factorial((n - k)::INT)))) AS s FROM (SELECT DISTINCT len(list_distinct(symbols)) AS n FROM ({workloads.SQL['events']}) WHERE len(symbols) > 0) a, (SELECT unnest(range(1, 8)) AS k) b WHERE k <= n GROUP BY n) SELECT n, s::BIGINT AS schemas, [1, 3, 13, 75, 541, 4683, 47293][n]::BIGINT AS ordered_bell, round(pow(4, n) * factorial(n::INT)::DOUBLE / (2 * pow(ln(2), n + 1)), 3) AS asymptotic FROM t",
        "orders_accepted_planted": _sql("planted", "SELECT element, round((SELECT coalesce(sum(ln(i)), 0) FROM range(1, 40) r(i) WHERE i <= list_sum(s)) - (SELECT coalesce(sum(ln(i)), 0) FROM range(1, 40) r(i), (SELECT unnest(s) AS z) WHERE i <= z), 6) AS log_orders, (factorial(list_sum(s)::INTEGER) // list_reduce(list_transform(s, lambda z: factorial(z::INTEGER)), lambda a, b: a * b))::VARCHAR AS orders FROM (SELECT element, list(n) AS s FROM factors GROUP BY element)"),
        "shuffle_words": f"""WITH RECURSIVE days AS (SELECT DISTINCT list_filter(symbols, lambda s: s IN ('click', 'view')) AS u, list_filter(symbols, lambda s: s NOT IN ('click', 'view')) AS v FROM ({workloads.SQL['events']})),
          m AS (SELECT u, v, 0 AS i, 0 AS j, []::VARCHAR[] AS w FROM days UNION SELECT u, v, i + c, j + 1 - c, list_append(w, CASE WHEN c = 1 THEN u[i + 1] ELSE v[j + 1] END) FROM m, (VALUES (0), (1)) t(c) WHERE CASE WHEN c = 1 THEN i < len(u) ELSE j < len(v) END)
          SELECT DISTINCT array_to_string(u, ' ') AS u, array_to_string(v, ' ') AS v, array_to_string(w, ' ') AS word FROM m WHERE i = len(u) AND j = len(v)""",
        "hardness_witness": f"SELECT 'graph' AS element, x, y FROM ({_sql('events', 'conflicts')})",
        "density_cube": "SELECT event_type, hour(ts) AS hour, count(*) AS n, grouping(event_type, hour(ts))::BIGINT AS level FROM events GROUP BY CUBE (event_type, hour(ts))",
        "orders_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(max(o_totalprice), 2) AS most FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
        "roles_pivot": "SELECT conv_id, count(*) FILTER (WHERE role = 'assistant') AS assistant, count(*) FILTER (WHERE role = 'system') AS system, count(*) FILTER (WHERE role = 'user') AS user FROM conversations GROUP BY conv_id",
        "as_of_orders": "SELECT o_orderkey, lag(o_orderdate) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)::DATE::VARCHAR AS previous FROM orders",
        "range_pairs": "SELECT b.event_id, count(*) AS clicks FROM events b JOIN events a ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND floor(epoch(a.ts)) <= floor(epoch(b.ts)) AND floor(epoch(a.ts)) > floor(epoch(b.ts)) - 3600 GROUP BY b.event_id",
        "frequent_words": _sql("users", "SELECT * FROM (SELECT element, word, n, row_number() OVER (PARTITION BY element ORDER BY n DESC, word) AS place FROM (SELECT element, array_to_string(symbols, ' ') AS word, count(*) AS n FROM w GROUP BY ALL)) WHERE place <= 10"),
        "longest_runs": "SELECT user_id, max(n) AS longest FROM (SELECT user_id, g, count(*) AS n FROM (SELECT user_id, sum(c) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) = event_type THEN 0 ELSE 1 END AS c FROM events)) GROUP BY ALL) GROUP BY user_id",
        "unknown_words": _sql("pages", "SELECT any_value(word_id) AS word_id, s AS symbol FROM prof GROUP BY s HAVING count(*) = 1"),
    }
