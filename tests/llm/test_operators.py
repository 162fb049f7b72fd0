"""The operators against brute force, SQL and their edge cases."""

import math
import random
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from weft.llm import components, crosspolytope, decontamination, minhash, quality, seekable, toxicity, urls
from weft.llm.bpe import standard_vocabulary
from weft.llm.shared import Workspace, words_of


def smallest(links, nodes):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return {n: find(n) for n in nodes}


def test_components(spark):
    rng = random.Random(1)
    links = [(i, i + 1) for i in range(100, 160)] + [(rng.randrange(90), rng.randrange(90)) for _ in range(70)] + [(500, 400 + i) for i in range(50)]
    found = dict(components.components(spark.createDataFrame(links, "a long, b long"), Workspace(spark, "t")).collect())
    expected = smallest(links, {x for p in links for x in p})
    assert found == {n: r for n, r in expected.items() if any(n in p and p[0] != p[1] for p in links)}
    assert components.components(spark.createDataFrame([], "a long, b long"), Workspace(spark, "t")).count() == 0


# --- urls -------------------------------------------------------------------------------------------


def test_urls_against_plain_rules(spark):
    rules = [(h, p, v) for h, p, v in urls.STANDARD_RULES] + [("org", "/x", "block"), ("a.org", "", "allow"), ("org", "/fr/", "block"), (None, "/", "block")]
    given = [
        None, "", "no scheme", "http://", "http://NET", "http://x.Example.NET/en/a?b#c", "http://example.net/en", "https://a.example.com/de/1", "://org/fr/", "http://aorg/fr/x", "http://b.org/xyz",
        "http://a.org:80/", "http://a.org?x=/y", "http://a.org#/fr/", "http://É.ORG/fr/é", "ftp://u@c.org/fr/" + "z/" * 3000, "http://" + "a." * 2000 + "net/", "http://x.net/\n", "a://b://c.net/",
    ]
    given += given[5:8]
    frame = spark.createDataFrame([(i if i else None, u, "h") for i, u in enumerate(given)], "page_id long, url string, host string")
    lower = str.maketrans(urls.UPPER_LETTERS, urls.LOWER_LETTERS)
    import re

    def judge(url):
        if url is None or "://" not in url:
            return "", "", None, "allow"
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        tail = rest[len(host) :]
        path, host = (re.match(r"[^?#]*", tail)[0] if tail.startswith("/") else ""), host.translate(lower)
        fit = [(len(h + p), h + p, v) for h, p, v in rules if h and (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fit, default=(0, None, "allow"))
        return host, path, best[1], best[2]

    out = urls.judge(frame, spark.createDataFrame(rules, "host string, path string, verdict string")).collect()
    assert sorted((r.host, r.path, r.rule or "", r.verdict) for r in out) == sorted((h, p, r or "", v) for h, p, r, v in map(judge, given))
    assert urls.judge(frame.limit(0), spark.createDataFrame(rules, "host string, path string, verdict string")).count() == 0
    assert {r.verdict for r in urls.judge(frame, spark.createDataFrame([], "host string, path string, verdict string")).collect()} == {"allow"}


# --- near duplicates --------------------------------------------------------------------------------


def near_corpus():
    rng = random.Random(4)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(3000)]
    docs = []
    for _ in range(12):
        base = [rng.choice(vocabulary) for _ in range(rng.randrange(30, 150))]
        for _ in range(rng.randrange(2, 14)):
            w = list(base)
            for _ in range(rng.randrange(0, 7)):
                at = rng.randrange(len(w))
                w[at : at + rng.randrange(2)] = [rng.choice(vocabulary)]
            docs.append(" ".join(w))
    docs += [docs[0]] * 5 + ["a b", "A  b\n", "a", "", None, " \t", "x"] + [docs[3].upper()]
    rng.shuffle(docs)
    return [(i * 3 + 1, t) for i, t in enumerate(docs)]


@pytest.mark.parametrize("size", [4, 5])
def test_minhash_equals_brute_force(spark, size, monkeypatch):
    docs = near_corpus()

    def shingles(text):
        w = words_of(text.encode() if text else None)
        return {tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()

    sets = {i: shingles(t) for i, t in docs}
    ids = sorted(sets)
    links = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    root = smallest(links, ids)
    frame = spark.createDataFrame([(i, t, b"x") for i, t in docs] + [(None, "a b c d e f", b"x")], "doc_id long, text string, digest binary").repartition(6)
    found = minhash.near_duplicates(frame, size=size).collect()
    assert len(found) == len(docs) + 1
    for r in found:
        if r.doc_id is None:
            assert r.component_id is None and not r.kept
        else:
            assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), root[r.doc_id], root[r.doc_id] == r.doc_id), r
    assert minhash.near_duplicates(frame.limit(0)).count() == 0
    with pytest.raises(ValueError):
        minhash.near_duplicates(frame, percent=70)


def test_minhash_blocks_don_t_change_the_result(spark, monkeypatch):
    frame = spark.createDataFrame(near_corpus(), "doc_id long, text string")
    whole = sorted(map(tuple, minhash.near_duplicates(frame).collect()))
    monkeypatch.setattr(minhash, "BLOCK", 3)
    assert sorted(map(tuple, minhash.near_duplicates(frame).collect())) == whole


def test_signatures_estimate_similarity():
    rng = np.random.default_rng(3)
    ring = minhash._ring()
    a = rng.integers(0, 2**63, 900).astype(np.uint64)
    b = np.concatenate([a[:800], rng.integers(0, 2**63, 100).astype(np.uint64)])
    same = (minhash.signature(a, ring) == minhash.signature(b, ring)).mean()
    assert abs(same - 0.8) < 0.12


# --- embeddings -------------------------------------------------------------------------------------


def vectors():
    rng = np.random.default_rng(5)
    base = rng.standard_normal((60, 24))
    out = [list(map(float, v)) for v in base]
    for i in range(25):
        for _ in range(rng.integers(1, 9)):
            out.append(list(map(float, base[i] + rng.standard_normal(24) * rng.uniform(0, 0.33))))
    out += [out[0]] * 4 + [[2 * x for x in out[1]], None, [], [0.0] * 24, [float("nan")] * 24, [None] * 24, [float("inf")] + [0.0] * 23, out[2][:10], out[2][:10], [-0.0] + out[3][1:], [0.0] + out[3][1:]]
    return out


@pytest.mark.parametrize("block", [1000, 4])
def test_embeddings_equal_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(crosspolytope, "BLOCK", block)
    given = vectors()
    good = {i: np.array(v) for i, v in enumerate(given) if v and None not in v and np.isfinite(v).all() and np.any(v)}
    links = [(a, b) for a in good for b in good if a < b and len(good[a]) == len(good[b]) and good[a] @ good[b] / np.linalg.norm(good[a]) / np.linalg.norm(good[b]) >= 0.95]
    root, degree = smallest(links, range(len(given))), Counter(x for p in links for x in p)
    frame = spark.createDataFrame([(i, v, "x") for i, v in enumerate(given)] + [(None, given[0], "x")], "vec_id long, embedding array<double>, id string").repartition(5)
    for r in crosspolytope.near_duplicates(frame).collect():
        if r.vec_id is not None:
            assert (r.n_links, r.component_id, r.kept) == (degree[r.vec_id], root[r.vec_id], root[r.vec_id] == r.vec_id), r
    assert crosspolytope.near_duplicates(frame.limit(0)).count() == 0


def test_rotation_keeps_lengths_and_recall_is_planned():
    x = np.random.default_rng(1).standard_normal((5, 16))
    assert np.allclose((crosspolytope.hadamard(x) ** 2).sum(axis=1), 16 * (x**2).sum(axis=1))
    width, joined, tables = crosspolytope.layout(50_000, 64, 0.95)
    assert width == 64 and joined >= 2 and (1 - crosspolytope.share_found(width, joined, 0.95)) ** tables <= crosspolytope.MISS


# --- decontamination --------------------------------------------------------------------------------


@pytest.mark.parametrize("literals", [50_000, 0])
def test_leaks_equal_brute_force(spark, monkeypatch, literals):
    import re

    monkeypatch.setattr(decontamination, "LITERALS", literals)
    rng = random.Random(7)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(4)) for _ in range(500)]
    text = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    items = [(i, text(rng.randrange(6, 40))) for i in range(25)] + [(30, "one two three"), (31, ""), (32, None), (33, "ab ab ab ab ab ab ab ab"), (0, None)]
    docs = []
    for i in range(80):
        t = text(rng.randrange(0, 60))
        if i % 2:
            w = rng.choice(items[:25])[1].split()
            for _ in range(rng.randrange(0, 4)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            t = f"{t}\n{', '.join(w).upper()}! {text(rng.randrange(20))}"
        docs.append((i, t))
    docs += [(90, "One, two; THREE"), (91, None), (92, ""), (93, "ab " * 40), (94, "one two"), (None, items[0][1]), (95, docs[1][1]), (95, docs[1][1])]

    def parts(t):
        return [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]

    expected = {}
    for d, t in docs:
        if d is None:
            continue
        for i, s in items:
            w, v = parts(t), parts(s)
            if not v:
                continue
            k = min(5, len(v))
            grams = lambda x, k=k: [tuple(x[j : j + k]) for j in range(len(x) - k + 1)]
            a = Counter(grams(v))
            best = 0.0
            for start in range(len(w)):
                b = Counter(grams(w[start : start + len(v)]))
                both = sum((a & b).values())
                best = max(best, both / sum((a | b).values()))
            if best >= 0.8:
                expected[d, i] = best
    frame = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, item_id int")
    found = decontamination.matches(frame, spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id): round(r.similarity, 9) for r in found} == {k: round(v, 9) for k, v in expected.items()} and len(found) == len(expected)
    assert len(expected) > 8
    assert decontamination.matches(frame.limit(0), spark.createDataFrame(items, "item_id long, text string")).count() == 0
    assert decontamination.matches(frame, spark.createDataFrame([], "item_id long, text string")).count() == 0


@pytest.mark.parametrize("literals", [50_000, 0])
def test_leaks_at_any_place_of_a_window(spark, monkeypatch, literals):
    """Blocks swapped, words left out, put in and replaced: every pair of 0.8 or more is found, at its best window."""
    monkeypatch.setattr(decontamination, "LITERALS", literals)
    rng = random.Random(11)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(4)) for _ in range(700)]
    words = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    items = [(i, words(rng.randrange(30, 110))) for i in range(12)]
    docs = []
    for i in range(120):
        w = list(items[i % 12][1])
        if i % 3 == 0:
            at = rng.randrange(10, len(w) - 10)
            w = w[at:] + w[:at]
        for _ in range(rng.randrange(0, max(1, len(w) // 22))):
            at = rng.randrange(len(w))
            w[at : at + rng.randrange(2)] = words(rng.randrange(2))
        if i % 5 == 0:
            w = w[: len(w) - rng.randrange(12)]  # the document ends inside the item
        docs.append((i, words(rng.randrange(40)) + w + (words(rng.randrange(40)) if i % 5 else [])))
    docs += [(1000, docs[0][1]), (1000, words(50) + items[1][1]), (1000, items[1][1] + words(5))]
    expected, near = {}, 0
    grams = lambda x: [tuple(x[j : j + 5]) for j in range(len(x) - 4)]
    for d, w in docs:
        h = grams(w)
        for i, v in items:
            a, m = Counter(grams(v)), len(v) - 4
            if not set(h) & set(a):
                continue
            for start in range(len(h)):
                b = Counter(h[start : start + m])
                s = sum((a & b).values()) / sum((a | b).values())
                if s >= 0.8 and s > expected.get((d, i), 0):
                    expected[d, i] = s
    frame = spark.createDataFrame([(d, " ".join(w)) for d, w in docs], "doc_id long, text string").repartition(4)
    found = decontamination.matches(frame, spark.createDataFrame([(i, " ".join(v)) for i, v in items], "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id): round(r.similarity, 9) for r in found} == {k: round(v, 9) for k, v in expected.items()} and len(found) == len(expected)
    assert len(expected) > 80 and sum(s < 0.9 for s in expected.values()) > 15


def test_leak_of_swapped_blocks(spark):
    a, b = [f"a{i}" for i in range(60)], [f"b{i}" for i in range(40)]
    docs = spark.createDataFrame([(1, " ".join(["x"] * 30 + b + a + ["y"] * 9)), (2, " ".join(a + b)), (3, " ".join(a))], "doc_id long, text string")
    found = {r.doc_id: r for r in decontamination.matches(docs, spark.createDataFrame([(7, " ".join(a + b))], "item_id long, text string")).collect()}
    assert set(found) == {1, 2} and found[1].start == 30 and round(found[1].similarity, 2) == 0.92 and found[2].similarity == 1


# --- classifiers ------------------------------------------------------------------------------------


def labelled(spark):
    rng = random.Random(9)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(400)]
    docs, labels = [], []
    for i in range(600):
        w = [rng.choice(vocabulary) for _ in range(rng.randrange(5, 120))]
        toxic, good = i % 3 == 0, i % 4 != 0
        if toxic:
            w.insert(rng.randrange(len(w)), rng.choice(["grimbly", "gromple", "grunkle"]) + rng.choice(["", ",", "!"]))
        t = " ".join(w)
        docs.append((i, t if good else (t.upper().replace(" ", "!! ") if i % 8 else " ".join([w[0]] * len(w)) + " " + (w[-1] if not toxic else t))))
        labels.append((i, int(good), int(toxic)))
    return spark.createDataFrame(docs + [(1000, None), (1001, ""), (None, "a b")], "doc_id long, text string"), spark.createDataFrame(labels + [(2000, 1, 1), (None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")


def test_classifiers_on_held_out_rows(spark):
    docs, labels = labelled(spark)
    from weft.llm.labelled import judged

    for module, label, threshold, least in ((toxicity, "toxic", 0.5, 0.9), (quality, "quality", 0.3, 0.9)):
        scored = judged(module.score(docs, module.fit(docs, labels)), threshold).cache()
        assert scored.count() == 603 and not scored.where("score is null or score < 0 or score > 1").count()
        for r in scored.where("doc_id is not null").limit(50).collect():
            assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
        found = scored.where("held_out").join(labels, "doc_id").select(F.avg((F.col("predicted") == F.col(label)).cast("double"))).first()[0]
        assert found >= least, (label, found)
        again = judged(module.score(docs.repartition(3), module.fit(docs.repartition(5), labels)), threshold)
        first, second = (dict(map(tuple, x.select("doc_id", "score").dropna().collect())) for x in (scored, again))
        assert first.keys() == second.keys() and all(abs(first[k] - second[k]) < 1e-4 for k in first)
        none = module.score(docs, module.fit(docs, labels.limit(0)))
        assert {r.score for r in none.collect()} == {0.0} and module.score(docs.limit(0), None).count() == 0
    assert toxicity.keep_clean(docs.withColumn("score", F.lit("x")), toxicity.fit(docs, labels)).columns == ["doc_id", "text", "score"]


def test_long_texts_pool_like_one_piece(monkeypatch):
    network = toxicity.Network()
    texts = [toxicity.read_text(" ".join(f"w{i % 97}" for i in range(n)).encode())[0] for n in (0, 1, 2, 500, 1200)]
    whole = network.pooled(texts)
    monkeypatch.setattr(toxicity, "CHUNK", 64)
    assert np.allclose(whole, network.pooled(texts), atol=1e-6)
    assert np.allclose(whole[3], network.pooled([texts[3]])[0], atol=1e-6)


# --- token files ------------------------------------------------------------------------------------


def test_token_files(spark, tmp_path, monkeypatch):
    import zstandard
    from tokenizers import Tokenizer

    monkeypatch.setattr(seekable, "DOCS_PER_FILE", 40)
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    docs = docs.union(spark.createDataFrame([(10**6, None), (-5, ""), (None, "x")], "doc_id long, text string")).repartition(7)
    manifest = seekable.write(docs, f"file://{tmp_path}/ids", standard_vocabulary())
    library = Tokenizer.from_file(standard_vocabulary())
    at, expected = 0, {}
    for r in sorted(docs.where("doc_id is not null").collect()):
        ids = library.encode(r.text or "", add_special_tokens=False).ids + [0]
        expected[r.doc_id] = (at, ids)
        at += len(ids)
    found = seekable.read(manifest).collect()
    assert {r.doc_id: (r.start, r.ids) for r in found} == expected and len(found) == len(expected)
    for r in seekable.read(manifest, digests=True).collect():
        start, ids = expected[r.doc_id]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    some = manifest.where("file_no = 1").select("file_no", F.array(F.lit(2), F.lit(0)).alias("documents"))
    part = seekable.read(manifest, some).collect()
    assert len(part) == 2 and all(expected[r.doc_id] == (r.start, r.ids) for r in part)
    file = sorted(manifest.collect())[0]
    raw = open(file.uri.removeprefix("file://"), "rb").read()
    plain = b"".join(zstandard.ZstdDecompressor().decompress(raw[a:b], max_output_size=1 << 24) for a, b in zip(*[seekable.Reader(file.uri).starts[:-2], seekable.Reader(file.uri).starts[1:-1]]))
    assert len(plain) == 2 * file.tokens
    path = file.uri.removeprefix("file://")
    damaged = bytearray(raw)
    damaged[12] ^= 1
    open(path, "wb").write(damaged)
    with pytest.raises(Exception):
        reader = seekable.Reader(file.uri)
        [reader.ids(i) for i in range(len(reader))]
    assert seekable.write(docs.limit(0), f"file://{tmp_path}/none", standard_vocabulary()).count() == 0


# --- SQL --------------------------------------------------------------------------------------------


@pytest.mark.parametrize("module, query, sql", [(urls, "op4_url_filter", "OP4_SQL"), (crosspolytope, "op2_embedding_dedup", "OP2_SQL")])
def test_queries_equal_their_sql(spark, module, query, sql):
    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("pages", "embeddings", "documents", "benchmark"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    frame = getattr(module, query)(spark, d)
    mine = sorted(map(str, map(tuple, frame.select(sorted(frame.columns)).collect())))
    theirs = con.execute(f"select {', '.join(sorted(frame.columns))} from ({getattr(module, sql)})").fetchall()
    assert mine == sorted(map(str, theirs))


def test_pipeline_stages(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (10**6, "", "en", "s", 0), (10**6 + 1, None, "en", "s", None)], docs.schema)
    given = docs.union(odd)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, given, d)
        assert out.columns == docs.columns and out.dtypes == docs.dtypes
        assert out.where("doc_id = 1000001").count() == 1, name
        given = Workspace(spark, "t").keep(out, name)
    assert 0 < given.count() < docs.count()
    ids = corpus_pipeline.STAGES[-1][1](spark, given, d)
    assert ids.count() == given.count()
    assert math.isclose(ids.where("decoded = ''").count(), given.where("text is null or text = ''").count())
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_copies", "repeats", "leaks", "tokens"]
