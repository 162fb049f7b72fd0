import random

import numpy as np
import pytest

from weft.llm import repeats
from weft.llm.shared import may_hold, sieve_of


def words(rng, n, letters="abcdefghij"):
    return ["".join(rng.choice(letters) for _ in range(rng.randrange(2, 7))) for _ in range(n)]


def marks(docs):
    """Words of passages of 50 words that also stand in a document with a smaller key."""
    seen = {}
    for key, w in docs:
        for i in range(len(w) - 49):
            g = tuple(w[i : i + 50])
            seen[g] = min(seen.get(g, key), key)
    out = {}
    for key, w in docs:
        hit = np.zeros(len(w), bool)
        for i in range(len(w) - 49):
            if seen[tuple(w[i : i + 50])] < key:
                hit[i : i + 50] = True
        out[key] = hit
    return out


def corpus():
    rng = random.Random(5)
    shared = [words(rng, n) for n in (50, 51, 60, 75, 120, 300)]
    docs = []
    for key in range(60):
        w = words(rng, rng.randrange(0, 120))
        for _ in range(rng.randrange(0, 3)):
            w += rng.choice(shared) + words(rng, rng.randrange(0, 60))
        docs.append((key, w))
    docs += [(100 + i, docs[i][1]) for i in range(20)]  # copies
    docs += [(200 + i, docs[30 + i][1][: rng.randrange(200)]) for i in range(10)]
    docs += [(300, ["again"] * 400), (301, ["again"] * 120), (302, [])]
    common_ = words(rng, 70)
    docs += [(400 + i, words(rng, 30) + common_ + words(rng, 30)) for i in range(40)]
    return docs


@pytest.mark.parametrize("group", [1000, 5])
def test_runs_against_brute_force(spark, monkeypatch, group):
    monkeypatch.setattr(repeats, "GROUP", group)
    docs = corpus()
    frame = spark.createDataFrame([(k, " ".join(w).upper() if k % 2 else "\n".join(w), "x") for k, w in docs] + [(None, None, "n"), (900, None, "n"), (901, "", "e")], "doc_id long, text string, of string").repartition(5)
    found, covers = {}, {}
    for r in repeats.find(frame).collect():
        found.setdefault(r.doc_id, []).append((r.start, r.end))
        assert r.of < r.doc_id
    for key, hit in marks(docs).items():
        own = np.zeros(len(hit), bool)
        for a, b in found.get(key, []):
            own[a:b] = True
        assert not (own & ~hit).any(), key  # nothing is cut that doesn't repeat
        missed = np.flatnonzero(hit & ~own)  # at most edges that fit one more document by chance
        assert len(missed) <= 3 and all(own[max(0, m - 3) : m + 4].any() for m in missed), (key, missed, found.get(key))
        covers[key] = own
    assert sum(hit.sum() for hit in marks(docs).values()) - sum(c.sum() for c in covers.values()) <= 20
    cut = {r.doc_id: r for r in repeats.remove(frame, repeats.find(frame)).collect()}
    assert len(cut) == len(docs) + 3 and cut[900].text is None and cut[901].text == "" and cut[None].of == "n"
    for key, w in docs:
        assert cut[key].text.lower().split() == [x for x, h in zip(w, covers[key]) if not h]
    assert repeats.find(frame.limit(0)).count() == 0


def covered(spark, docs):
    out = {key: np.zeros(len(w), bool) for key, w in docs}
    for r in repeats.find(spark.createDataFrame([(k, " ".join(w)) for k, w in docs], "doc_id long, text string")).collect():
        out[r.doc_id][r.start : r.end] = True
    return out


def test_longer_passages_through_a_crowded_line_are_whole(spark, monkeypatch):
    """Fours share 50 words through a line of 44 that the earliest document holds alone."""
    monkeypatch.setattr(repeats, "GROUP", 20)
    rng = random.Random(8)
    line = words(rng, 44)
    docs = [(0, words(rng, 40) + line + words(rng, 40))]
    keys = list(range(1, 241))
    rng.shuffle(keys)
    for i in range(0, 240, 4):
        before, after = words(rng, 3), words(rng, 3)
        docs += [(k, words(rng, 40) + before + line + after + words(rng, 40)) for k in keys[i : i + 4]]
    expected, got = marks(docs), covered(spark, docs)
    assert sum(m.sum() for m in expected.values()) == 180 * 50
    assert all((got[k] == expected[k]).all() for k in expected)


@pytest.mark.parametrize("group", [1000, 5])
def test_nested_passages_are_exact(spark, monkeypatch, group):
    """Many documents hold other parts of the same words; nearer ones in sorted order share less in total."""
    monkeypatch.setattr(repeats, "GROUP", group)
    rng = random.Random(12)
    base = words(rng, 90)
    docs = []
    for key in rng.sample(range(300), 120):
        a, n = rng.randrange(0, 60), rng.randrange(30, 75)
        docs.append((key, words(rng, 20) + base[a : a + n] + words(rng, 20)))
    part = words(rng, 10) + base + words(rng, 60)
    docs += [(1000, part + part), (1001, part)]  # one surrounding twice in the earliest document
    expected, got = marks(docs), covered(spark, docs)
    assert all((got[k] == expected[k]).all() for k in expected)


def exchanged(spark, docs):
    """Bytes that ``find`` writes to exchanges, without joins that send a table around unasked."""
    context = spark.sparkContext
    put = {k: spark.conf.get(k, None) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")}
    store = context._jsc.sc().statusStore()

    def stages():
        context._jsc.sc().listenerBus().waitUntilEmpty()
        listed = store.stageList(None, False, False, context._gateway.new_array(context._jvm.double, 0), context._jvm.java.util.ArrayList())
        return {(x.stageId(), x.attemptId()): x.shuffleWriteBytes() for x in (listed.apply(i) for i in range(listed.size()))}

    before = set(stages())
    try:
        for k in put:
            spark.conf.set(k, "-1")
        repeats.find(docs).collect()
    finally:
        for k, v in put.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    return sum(n for k, n in stages().items() if k not in before)


def test_surroundings_are_exchanged_no_more_than_needed(spark):
    """Once for their classes, and once more (by either side) for those that share a group with others."""
    rng = random.Random(21)
    shared = [words(rng, 60) for _ in range(300)]
    docs = []
    for key in range(600):
        w = []
        for _ in range(4):
            w += rng.choice(shared) + words(rng, 12)
        docs.append((key, " ".join(w)))
    docs = spark.createDataFrame(docs, "doc_id long, text string").repartition(4)
    own = docs.select("doc_id", "text")
    suffixes = repeats._suffixes(own).count()
    assert exchanged(spark, docs) < 4 * suffixes * (repeats.PASSAGE + repeats.REACH) * repeats.WIDE


def test_rows_that_repeat_a_key_with_other_texts(spark):
    """Each row's suffixes are its own; a place of the longer text need not be in the shorter one."""
    rng = random.Random(3)
    part, long_ = words(rng, 60), words(rng, 200)
    docs = spark.createDataFrame([(1, " ".join(long_ + part)), (2, " ".join(words(rng, 150) + part)), (2, " ".join(words(rng, 55)))], "doc_id long, text string")
    assert [(r.doc_id, r.start, r.end, r.of) for r in repeats.find(docs).collect()] == [(2, 150, 210, 1)]


def test_sieves_hold_their_names(spark):
    rng = np.random.default_rng(4)
    names, others = rng.integers(0, 1 << 64, 5000, np.uint64), rng.integers(0, 1 << 64, 50_000, np.uint64)
    sieve = sieve_of(spark.createDataFrame([(int(x),) for x in names.view(np.int64)], "name long"))
    assert may_hold(sieve, names).all() and may_hold(sieve, others).mean() < 0.03
    assert not may_hold(sieve_of(spark.createDataFrame([], "name long")), others).any()


def test_one_document_alone_in_a_large_group(spark, monkeypatch):
    """Groups of more than GROUP suffixes of one document meet nothing; its passages elsewhere are found."""
    monkeypatch.setattr(repeats, "GROUP", 5)
    rng = random.Random(33)
    line, part = words(rng, 40), words(rng, 80)
    docs = [(0, [w for _ in range(30) for w in line + words(rng, 3)] + part), (1, words(rng, 30) + part), (2, words(rng, 20) + line * 2)]
    expected, got = marks(docs), covered(spark, docs)
    assert all((got[k] == expected[k]).all() for k in expected)


def test_cutting_keeps_other_white_space():
    assert repeats.without("a\n b  c\td e ".encode(), [(1, 3)]) == b"a\n d e "
    assert repeats.without(b"a b", [(0, 2)]) == b""
