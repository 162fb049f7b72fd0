"""Relations, learners, validation, measures and the incremental learner on Spark."""

import random

import pytest
from pyspark.sql import functions as F

from weft import catalogue, workloads
from weft.operators import baselines, extensions, measures, precedence, validate
from weft.plans import learn
from weft.sources import generate, words
from weft.streaming import incremental
from weft.types import assert_corpus


def rows(frame, *columns):
    return sorted(tuple(r) for r in frame.select(*columns).collect())


@pytest.fixture(scope="module")
def examples(spark):
    return generate.examples(spark).cache()


@pytest.fixture(scope="module")
def sample(spark):
    rng = random.Random(3)
    made = [(f"e{rng.randrange(12)}", "".join(rng.choice("abcde"[: rng.randrange(1, 6)]) for _ in range(rng.randrange(7)))) for _ in range(200)]
    return generate.from_words(spark, made).cache()


def test_plans_for_pairs_agree(sample):
    a, b, c = (rows(precedence.pairs(sample, p), "element", "x", "y", "n_words") for p in ("profile", "selfjoin", "positions"))
    assert a == b == c
    long = sample.select("element", "word_id", F.explode_outer(F.transform("symbols", lambda s, i: F.struct(i.alias("i"), s.alias("s")))).alias("p"))
    held = words.long_rows(long.select("element", "word_id", "p.i", "p.s"), "element", "word_id", ["i"], "s")
    assert rows(precedence.pairs_of(precedence.signatures(precedence.profile_from_rows(held))), "element", "x", "y", "n_words") == a
    assert rows(precedence.pairs(sample.repartition(7).union(sample)), "element", "x", "y") == [r[:3] for r in a]


def test_worked_relations(examples):
    pairs = precedence.pairs(examples.where("element = 'repeats'"))
    assert ["".join(r) for r in rows(pairs, "x", "y")] == ["ab", "ac", "ad", "bc", "bd", "cd", "db", "dc"]
    assert ["".join(r) for r in rows(precedence.conflicts(pairs), "x", "y")] == ["bd", "cd", "db", "dc"]
    assert ["".join(r) for r in rows(precedence.stable(pairs), "x", "y")] == ["ab", "ac", "ad", "bc"]


def test_worked_schemas(examples):
    found = {(r.element, r.learner): r.text for r in learn.compare_learners(examples).collect()}
    for learner in ("exact", "is", "dag"):
        assert found["one_word", learner] == "a b c d"
        assert found["two_words", learner] == found["rivals", learner] == "a b c & d"
        assert found["repeats", learner] == "a* b c? & d+"
        assert found["empty_and_one", learner] == "a?" and found["single_letters", learner] == "a+"
    assert found["broken_path", "exact"] == "x? b? c d y? & a"
    assert len(found["cyclic", "exact"].split(" & ")) == 2


def test_every_learner_covers_its_sample(sample, examples):
    for corpus in (sample, examples):
        found = learn.compare_learners(corpus).unionByName(learn.learn(corpus, ("greedy", "fewest", "exact_listed"))).unionByName(learn.by_precedence_dag(corpus, merge="tree").withColumn("learner", F.lit("dag tree")))
        found = found.unionByName(baselines.multiplicities_only(corpus)).unionByName(baselines.star_schema_rows(corpus))
        cover = validate.coverage(corpus, found).collect()
        assert {r.learner for r in cover} >= {"exact", "is", "dag", "dag tree", "fewest", "multiplicity", "star"} and all(r.coverage == 1.0 for r in cover)
    assert not baselines.chain_accepts(sample, baselines.ordered_chain(sample)).where("not accepted").count()
    assert not measures.compare(learn.by_independent_sets(sample), baselines.star_schema_rows(sample)).where("relation not in ('subset', 'equal')").count()


def test_spark_membership_equals_single_words(sample):
    from weft.functions import schema as S

    schemas = learn.by_independent_sets(sample)
    known = {r.element: S.parse(r.text) for r in schemas.collect()}
    other = measures.perturbed(sample).union(sample)
    held = {r.word_id + r.element: r.symbols for r in other.collect()}
    for r in validate.accepts(other, schemas).collect():
        assert r.reason == S.accepts(known[r.element], held[r.word_id + r.element])


def test_planted_layouts_are_found_again(spark, sf):
    found = catalogue.planted_recovery(spark, "/root/testdata/sf0.01").collect()
    assert len(found) == 12 and all(r.recovered for r in found)
    read = {(r.element, r.learner): r.recovered for r in catalogue.planted_recovery_dag(spark, sf).collect()}
    assert len(read) == 12 and all(read[n, o] for n in ("inproceedings", "proceedings", "phdthesis", "www") for o in ("dag lex",))
    assert rows(catalogue.schema_dag_orders(spark, sf), "reading") == [("first_seen",), ("freq",), ("lex",)]


def test_workloads_of_the_survey(spark):
    d = "/root/testdata/sf0.01"
    assert learn.exact(workloads.pages(spark, d)).first().text == "html head meta title style script body nav ul a+ div article h1 b+ footer & li+ br+ & p+"
    assert learn.exact(workloads.conversations(spark, d)).first().text == "system? assistant* & user+"
    parents = {r.element: r.text for r in learn.exact(workloads.page_children(spark, d)).collect()}
    assert parents["head"] == "meta title style script" and parents["ul"] == "li+" and parents["b"] == "br p*"


def test_finished_graphs_of_the_workloads(spark, sf):
    """No edge of the word-by-word graph joins symbols in conflict, in any reading order."""
    from weft.operators import dag

    for name in ("events", "lineitem", "planted"):
        corpus = workloads.BUILDERS[name](spark, sf)
        read: dict = {}
        for w in learn.collapsed(corpus).collect():
            read.setdefault(w.element, []).append(w)
        for row in learn.graph_rows(precedence.signatures(precedence.profile(corpus))).collect():
            mult, conflicts, _ = learn._graphs(row)
            for order in ("first_seen", "lex", "freq"):
                g = dag.PrecedenceGraph(mult)
                for w in sorted(read[row.element], key=learn._order(order)):
                    g.absorb(list(w.symbols))
                assert not [(x, y) for x, y in g.edges() if y in conflicts[x]], (name, row.element, order)


def test_reading_order_counts_up(spark):
    given = [("e", "10", ["b", "a"]), ("e", "9", ["a", "b"]), ("e", "100", ["a", "b"]), ("e", "11", ["a", "a", "b"])]
    words = spark.createDataFrame(given, "element string, word_id string, symbols array<string>")
    assert [(r.first, r.n_words) for r in learn.collapsed(words).orderBy("n_words").collect()] == [("10", 1), ("9", 3)]


def test_words_without_a_schema_are_not_accepted(spark):
    w = generate.from_words(spark, [("a", "xy"), ("b", "x"), ("b", "yz")])
    schemas = learn.exact(w.where("element = 'a'"))
    assert sorted((r.element, r.learner or "", r.accepted, r.reason) for r in validate.accepts(w, schemas).collect()) == [("a", "exact", True, "ok"), ("b", "", False, "no_schema"), ("b", "", False, "no_schema")]
    assert {(r.element, r.words, r.accepted) for r in validate.coverage(w, schemas).collect()} == {("a", 1, 1), ("b", 2, 0)}


def test_choices_keep_the_sample(spark, sample):
    import re

    schemas = learn.exact(sample)
    with_choices = {r.element: r.text for r in extensions.choices_in_factors(sample, schemas).collect()}
    assert with_choices.keys() == {r.element for r in schemas.collect()}
    for r in sample.collect():
        for factor in with_choices[r.element].split(" & "):
            pattern = "".join(factor.split(" "))
            own = set(re.findall("[a-e]", factor))
            assert re.fullmatch(pattern, "".join(s for s in r.symbols if s in own)), (r, factor)
    w = generate.from_words(spark, [("e", "ac"), ("e", "bc"), ("e", "ac")])
    assert extensions.choices_in_factors(w, learn.exact(w)).first().text == "(a|b) c"


def test_frequent_pairs_by_projection(spark, sf):
    w = workloads.conversations(spark, sf)
    assert rows(extensions.frequent_by_projection(w, "conversation", 0.5), "x", "y", "support") == rows(extensions.frequent_precedence(w, 0.5), "x", "y", "support")


def test_languages_against_the_chain_baseline(spark, sample):
    found = measures.compare_chain(learn.compare_learners(sample), baselines.ordered_chain(sample)).collect()
    assert {r.relation for r in found} <= {"equal", "subset", "superset", "incomparable"} and len(found) == 3 * sample.select("element").distinct().count()


def test_nulls_fail_in_learners(spark):
    bad = spark.createDataFrame([("e", "1", ["a", None])], "element string, word_id string, symbols array<string>")
    for learned in (learn.exact(bad), learn.by_precedence_dag(bad)):
        with pytest.raises(Exception, match="null element"):
            learned.collect()


def test_measures_of_the_examples(examples):
    found = learn.learn(examples.where("element in ('rivals', 'repeats')"), ("exact", "is"))
    assert rows(measures.interleavings(found), "element", "learner", "interleavings") == [("repeats", "exact", 1), ("repeats", "is", 1), ("rivals", "exact", 1), ("rivals", "is", 1)]
    assert {r.orders for r in measures.log_orders(found).collect()} == {"4"}
    assert rows(measures.gap(found), "more_factors", "first_difference") == [(0, 0), (0, 0)]
    graph_rows = learn.graph_rows(precedence.signatures(precedence.profile(examples)))
    assert all(r.minimal for r in measures.minimality(found, graph_rows).collect())
    assert {r.block_tokens for r in measures.length(found.where("element = 'rivals' and learner = 'is'")).collect()} == {4 * 4 + 3.0}


def test_folded_batches_equal_one_pass(sample):
    parts = sample.withColumn("b", F.pmod(F.xxhash64("word_id"), F.lit(3)))
    state = None
    for b in (2, 0, 1, 0):
        state = incremental.fold(state, incremental.batch_state(parts.where(F.col("b") == b).drop("b"), b))
    whole = rows(learn.learn(sample, ("exact", "is")), "element", "learner", "words", "text")
    assert rows(incremental.schemas(state, ("exact", "is")), "element", "learner", "words", "text") == whole
    assert rows(incremental.schemas(incremental.compact(state, 1), ("exact", "is")), "element", "learner", "words", "text") == whole
    assert incremental.changed(state, state).count() == 0


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    source = tmp_path / "in"
    events.repartition(1).write.parquet(str(source))
    table = incremental.StateTable(spark, str(tmp_path / "state"))
    stream = incremental.session_words(spark.readStream.schema(events.schema).parquet(str(source)))
    run = stream.writeStream.foreachBatch(table.sink()).option("checkpointLocation", str(tmp_path / "check")).outputMode("append").trigger(availableNow=True).start()
    assert run.awaitTermination(120)
    closed = words.sessions(events).join(events.select(F.max(F.col("ts").cast("timestamp")).alias("m")), how="cross")
    last = events.select(F.max("ts").cast("timestamp")).first()[0]
    ends = events.select(F.col("user_id").cast("string").alias("element"), F.col("ts").cast("timestamp").alias("ts")).groupBy("element", F.session_window("ts", "6 hours").alias("w")).count()
    kept = ends.where(F.col("w.end") <= F.lit(last) - F.expr("INTERVAL 1 DAY")).select("element", F.concat_ws("/", "element", F.col("w.start").cast("string")).alias("word_id"))
    batch = incremental.batch_state(closed.drop("m").join(kept, ["element", "word_id"]))
    assert rows(incremental.graph_rows(table.read()), "element", "words") == rows(incremental.graph_rows(batch), "element", "words")
    assert rows(incremental.schemas(table.read()), "element", "text", "learner") == rows(incremental.schemas(batch), "element", "text", "learner")


def test_edges_of_the_corpus(spark):
    empty = generate.from_words(spark, [])
    assert learn.compare_learners(empty).count() == 0 and precedence.pairs(empty).count() == 0
    blank = generate.from_words(spark, [("e", ""), ("e", "")])
    assert [r.text for r in learn.learn(blank, ("is",)).collect()] == [""] and validate.coverage(blank, learn.exact(blank)).first().coverage == 1.0
    with pytest.raises(Exception, match="null element"):
        assert_corpus(spark.createDataFrame([("e", "1", ["a", None])], "element string, word_id string, symbols array<string>")).collect()
    with pytest.raises(ValueError):
        assert_corpus(spark.range(1))
    wide = spark.createDataFrame([("e", "1", ["é", "中 文", "é"], 5)], "element string, word_id string, symbols array<string>, x int")
    assert learn.exact(assert_corpus(wide)).first().text in ("é+ & 中 文", "中 文 & é+")


def test_extensions_and_baselines(spark):
    w = generate.from_words(spark, [("e", "ab"), ("e", "c"), ("e", "abc"), ("e", "d")])
    assert rows(extensions.exclusive_pairs(w), "x", "y") == [("a", "d"), ("b", "d"), ("c", "d")]
    assert rows(extensions.frequent_precedence(w, 0.5), "x", "y", "support") == [("a", "b", 0.5)]
    assert baselines.disjunctive_multiplicities(w).first().text == "(a|d)? & b? & c?"
    assert rows(baselines.global_order(generate.from_words(spark, [("e", "ab"), ("e", "ab"), ("e", "ba")])), "x", "y", "share") == [("a", "b", 0.666667)]
    v, e = spark.createDataFrame([("a",), ("b",), ("c",)], "v string"), spark.createDataFrame([("a", "b")], "x string, y string")
    assert rows(precedence.conflicts(precedence.pairs(generate.words_from_graph(v, e))), "x", "y") == [("a", "b"), ("b", "a")]


def test_plan_has_no_product_and_reads_few_columns(spark, sf):
    plan = precedence.pairs(workloads.lineitem(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan and "l_extendedprice" not in plan


def test_sql_functions_and_sinks(spark, sf, tmp_path):
    from weft.functions import sql
    from weft.sources import tables

    sql.register_all(spark)
    assert spark.sql("SELECT accepts_word(array('a', 'b'), 'a b') AS ok").first().ok
    assert spark.sql("SELECT count(*) AS n FROM maximal_sets(array('a', 'b', 'c'), array('a|b'))").first().n == 2
    found = learn.exact(workloads.conversations(spark, sf))
    tables.write_schemas(found, str(tmp_path / "s"))
    tables.write_registry(found, str(tmp_path / "j"))
    assert tables.read_schemas(spark, str(tmp_path / "s")).count() == 1 and spark.read.json(str(tmp_path / "j")).count() == 1


def test_catalogue_names():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())


def test_catalogue_reads_the_whole_word_by_word_graph(spark, sf):
    from weft.operators import dag

    known = catalogue.queries()
    assert all(f"schema_dag_tree_{n}" in known and f"schema_dag_{n}" in known for n in catalogue.TWO_ROUNDS)
    corpus = workloads.segments(spark, sf)
    found = {r.element: r.text for r in known["schema_dag_segments"](spark, sf).collect()}
    read = {}
    for w in learn.collapsed(corpus).collect():
        read.setdefault(w.element, []).append(w)
    for row in learn.graph_rows(precedence.signatures(precedence.profile(corpus))).collect():
        mult, conflicts, after = learn._graphs(row)
        g = dag.PrecedenceGraph(mult)
        for w in sorted(read[row.element], key=learn._order("first_seen")):
            g.absorb(list(w.symbols))
        chains, repaired = dag.chains(g, conflicts, after)
        assert found[row.element] == learn._finished(row, "dag", chains, mult, "ok", repaired)[-1]
