"""Every registered query on tables with nulls, empties, repeated rows and clashing names, and on empty tables; classifiers and the pipeline against plain loops."""

import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from weft.llm import queries, quality, toxicity
from weft.llm.shared import words_of

#: Columns that each query's contract names; result rows of op3 and op6 are matches and runs.
COLUMNS = {
    "op1_toxicity": "doc_id held_out score predicted",
    "op2_embedding_dedup": "vec_id n_links component_id kept",
    "op3_decontamination": "doc_id item_id start n_words similarity",
    "op4_url_filter": "page_id host path rule verdict",
    "op5_quality": "doc_id held_out score predicted",
    "op6_suffix_dedup": "doc_id start end of",
    "op7_bpe": "doc_id n_tokens ids_sha256 decoded_sha256",
    "op8_token_output": "doc_id start n_tokens ids_crc32",
    "op9_lm_scoring": "doc_id held_out n_tokens n_known train_tokens base_score score",
    "op10_minhash": "doc_id n_shingles component_id kept",
    "pipeline": "doc_id n_tokens ids decoded",
}
ODD = {
    "documents": [(10**6, None), (10**6 + 1, ""), (10**6 + 2, " \n\t"), (10**6 + 3, "word " * 30_000), (None, "a text without an id")],
    "pages": [(10**6, None), (10**6 + 1, ""), (10**6 + 2, "no scheme"), (10**6 + 2, "no scheme")],
    "benchmark": [(10**6, None), (10**6 + 1, "")],
}


@pytest.fixture(scope="module")
def folders(spark, sf, tmp_path_factory):
    """(odd tables, empty tables)."""
    odd, empty = tmp_path_factory.mktemp("odd"), tmp_path_factory.mktemp("empty")
    for name in ("documents", "embeddings", "pages", "benchmark", "labels"):
        given = spark.read.parquet(f"{sf}/{name}.parquet")
        given.limit(0).write.parquet(f"{empty}/{name}.parquet")
        more = given.union(given.limit(3))  # repeated rows
        if name in ODD:
            key, value = given.columns[0], "url" if name == "pages" else "text"
            rows = spark.createDataFrame(ODD[name], f"{key} long, {value} string")
            more = more.unionByName(rows, allowMissingColumns=True)
        if name == "labels":
            more = more.union(spark.createDataFrame([(None, 1, 1), (3, None, None), (10**7, 0, 1)], given.schema))
        if name == "embeddings":
            rows = spark.createDataFrame([(10**6, None), (10**6 + 1, []), (10**6 + 2, [0.0] * 64), (10**6 + 3, [1.0] * 3000)], "vec_id long, embedding array<double>")
            more = given.unionByName(rows.withColumn("embedding", F.col("embedding").cast(given.schema["embedding"].dataType)), allowMissingColumns=True)
        for extra in ("_copy", "_leak", "_runs", "_run_key", "gone", "of", "score", "id", "row"):
            more = more.withColumn(extra, F.lit("x"))
        more.repartition(3).write.parquet(f"{odd}/{name}.parquet")
    return str(odd), str(empty)


@pytest.mark.parametrize("name", sorted(COLUMNS))
def test_queries_on_odd_and_empty_tables(spark, folders, name):
    odd, empty = folders
    query = queries.queries()[name]
    found = query(spark, odd)
    assert set(COLUMNS[name].split()) <= set(found.columns)
    rows = found.collect()
    source = {"op4_url_filter": "pages", "op2_embedding_dedup": "embeddings"}.get(name, "documents")
    table = spark.read.parquet(f"{odd}/{source}.parquet")
    if name in ("op3_decontamination", "op6_suffix_dedup"):
        assert rows and all(r.doc_id is not None for r in rows)
    elif name == "op8_token_output":
        assert len(rows) == table.where("doc_id is not null").count()
    elif name == "pipeline":
        assert 0 < len(rows) < table.count() and {10**6, 10**6 + 1, 10**6 + 2} <= {r.doc_id for r in rows}
        assert all(r.n_tokens == len(r.ids) for r in rows)
    else:
        assert len(rows) == table.count()
    assert query(spark, empty).count() == 0


def texts_of(spark, sf, n=50):
    return [r.text.encode() for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").limit(n).collect() if r.text]


def test_toxicity_scores_equal_a_plain_loop(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    network = toxicity.fit(docs, labels)
    texts = [*texts_of(spark, sf), b"one", b"two words", b"a b c"]
    both = [toxicity.read_text(t) for t in texts]
    found = network.scores([x for x, _ in both], np.array([y for _, y in both]))
    for (words, language), score in zip(both, found):
        vectors = [network.e[a].astype(float) + network.e[b] for a, b in words]
        vectors += [np.zeros(toxicity.DIMENSION)] * (toxicity.WIDTHS[-1] - 1)
        total = float(network.bias[0])
        for c, k in enumerate(toxicity.WIDTHS):
            for f in range(toxicity.FILTERS):
                best = max(sum(float(vectors[i + j] @ network.w[k][j][:, f]) for j in range(k)) + float(network.b[k][f]) for i in range(len(words)))
                total += max(best, 0.0) * float(network.out[c * toxicity.FILTERS + f])
        assert abs(score - 1 / (1 + math.exp(network.offsets[language] - total))) < 1e-4


def test_quality_scores_equal_a_plain_sum(spark, sf):
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit(docs, labels)
    x = [quality.features(t) for t in [*texts_of(spark, sf), b"", None]]
    place = lambda edges, value: sum(value >= e for e in edges)
    for row, score in zip(x, model.scores(np.array(x))):
        total = model.base + sum(model.tables[f][place(model.edges[f], row[f])] for f in range(len(row)))
        total += sum(values[place(model.coarse[a], row[a]), place(model.coarse[b], row[b])] for a, b, values in model.pairs)
        assert abs(score - 1 / (1 + math.exp(-total))) < 1e-9


def test_pipeline_equals_brute_force(spark, sf, tmp_path):
    """Stage by stage on a small corpus: scores, near copies by full sets, repeats by all windows, leaks by all windows, ids by the library."""
    import corpus_pipeline
    from tokenizers import Tokenizer

    from weft.llm.bpe import standard_vocabulary

    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 7))) for _ in range(900)]
    words = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    item, shared = words(60), words(70)
    docs = [(i, words(rng.randrange(5, 120))) for i in range(30)]
    docs += [(100 + i, list(docs[i][1])) for i in range(5)]
    docs += [(200 + i, [*docs[i + 5][1][:-1], "changed"]) for i in range(8)]
    docs += [(300 + i, words(20) + shared + words(20)) for i in range(6)]
    docs += [(400 + i, words(15) + item[: 60 - i] + words(15)) for i in range(3)] + [(403, words(9) + item[25:] + item[:25])]
    toxic = spark.read.parquet(f"{sf}/documents.parquet").join(spark.read.parquet(f"{sf}/labels.parquet").where("toxic = 1"), "doc_id").limit(5).collect()
    labelled = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").join(spark.read.parquet(f"{sf}/labels.parquet").select("doc_id"), "doc_id", "left_semi")
    given = [(i, " ".join(w)) for i, w in docs] + [(500 + i, r.text) for i, r in enumerate(toxic)] + [(600, None), (601, "")]
    # labels are of other documents than those that the stages work on
    mine = spark.createDataFrame([(i, t, None if t is None else len(t)) for i, t in given], "doc_id long, text string, n_chars long")
    moved = labelled.select((F.col("doc_id") + 10**6).alias("doc_id"), "text")
    moved.withColumn("n_chars", F.length("text").cast("long")).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{sf}/labels.parquet").withColumn("doc_id", F.col("doc_id") + 10**6).write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, " ".join(item))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    stages = dict(corpus_pipeline.STAGES)
    d = str(tmp_path)
    texts = lambda frame: {r.doc_id: r.text for r in frame.collect()}
    network = toxicity.fit(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"))
    read = {i: toxicity.read_text(t.encode() if t else None) for i, t in given}
    clean = {i: t for i, t in given if network.scores([read[i][0]], np.array([read[i][1]]))[0] < 0.5}
    kept = stages["toxicity"](spark, mine, d)
    assert texts(kept) == clean and {600, 601} <= set(clean)

    def sets(text, size=5):
        w = words_of(text.encode() if text else None)
        return {tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()

    root = {i: i for i in clean}
    find = lambda i: i if root[i] == i else find(root[i])
    for a in clean:
        for b in clean:
            x, y = sets(clean[a]), sets(clean[b])
            if a < b and x and y and 100 * len(x & y) >= 80 * len(x | y):
                low, high = sorted((find(a), find(b)))
                root[high] = low
    single = {i: t for i, t in clean.items() if find(i) == i}
    frame = kept.where(F.col("doc_id").isin(list(clean)))
    kept = stages["near_copies"](spark, frame, d)
    assert texts(kept) == single and len(single) < len(clean)

    seen: dict = {}
    for i, t in single.items():
        w = words_of(t.encode() if t else None)
        for j in range(len(w) - 49):
            seen[tuple(w[j : j + 50])] = min(i, seen.get(tuple(w[j : j + 50]), i))
    expected = {}
    for i, t in single.items():
        w = words_of(t.encode() if t else None)
        gone = {j + x for j in range(len(w) - 49) if seen[tuple(w[j : j + 50])] < i for x in range(50)}
        expected[i] = [x for j, x in enumerate(w) if j not in gone]
    cut = stages["repeats"](spark, kept, d)
    after = texts(cut)
    assert {i: words_of(t.encode() if t else None) for i, t in after.items()} == expected and any(len(words_of((single[i] or "").encode())) > len(w) for i, w in expected.items())
    assert all(r.n_chars == len(r.text) for r in cut.collect() if r.text is not None)

    def leaks(text):
        w = [x for x in re.split(r"[\W_]+", (text or "").lower()) if x]
        grams = lambda x: Counter(tuple(x[j : j + 5]) for j in range(len(x) - 4))
        a = grams(item)
        return any(10 * sum((a & b).values()) >= 8 * sum((a | b).values()) for b in (grams(w[j : j + len(item)]) for j in range(len(w))))

    left = {i: t for i, t in after.items() if not leaks(t)}
    kept = stages["leaks"](spark, cut, d)
    assert texts(kept) == left and len(left) < len(after)
    library = Tokenizer.from_file(standard_vocabulary())
    for r in stages["tokens"](spark, kept, d).collect():
        assert list(r.ids) == library.encode(left[r.doc_id] or "", add_special_tokens=False).ids and r.decoded == (left[r.doc_id] or "")


def test_a_vocabulary_without_some_bytes_raises():
    from weft.llm.pieces import PrefixEncoder

    class Small:
        ids, parts, merge = {b"a": 0, b"b": 1, b"ab": 2}, {2: (0, 1, 0)}, {(0, 1): 0}

    assert PrefixEncoder(Small).encode(b"aab") == [0, 2]
    for piece in (b"ac", b"cab", b"c"):
        with pytest.raises(ValueError):
            PrefixEncoder(Small).encode(piece)
