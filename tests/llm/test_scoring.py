import math
import zlib
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from weft.llm import scoring
from weft.llm.scoring import standard_ranks


def brute(rows):
    words = [(i, (t or "").encode().translate(scoring_lower()).split() + [b""]) for i, t in rows]
    train = Counter(w for i, ws in words if i is None or zlib.crc32(str(i).encode()) % 7 != 2 for w in ws)
    n, v = sum(train.values()), len(train)
    return [(len(ws), sum(train[w] > 0 for w in ws), n, sum(math.log10((train[w] + 1) / (n + v + 1)) for w in ws)) for _, ws in words]


def scoring_lower():
    from weft.llm.shared import LOWER

    return LOWER


def test_base_scores_equal_brute_force_and_the_model_is_better_than_chance(spark, monkeypatch):
    monkeypatch.setattr(scoring, "COMMON", 500)
    monkeypatch.setattr(scoring, "SHARE", 4)
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    odd = spark.createDataFrame([(10**6, None), (10**6 + 1, ""), (10**6 + 2, "ZqÉ \x1c zq"), (None, "a b"), (7, "again"), (10**6 + 3, "word " * 3000)], "doc_id long, text string")
    frame = docs.union(odd).withColumn("score", F.lit("x")).withColumn("id", F.lit(1))
    given = [(r.doc_id, r.text) for r in frame.collect()]
    expected = brute(given)
    rows = scoring.score(frame, standard_ranks()).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 5)) for r in rows) == sorted((i is None, i or 0, *x[:3], round(x[3], 5)) for i, x in zip([i for i, _ in given], expected))
    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 7 == 2) and r.score < 0 for r in rows)
    real = [r for r in rows if r.doc_id is not None and r.doc_id < 10**6 and r.held_out]
    # an id tells some 15 bits where nothing is known; texts that training never saw take far fewer
    ids = scoring.Ids(scoring.read_vocabulary(standard_ranks()))
    lengths = {i: len(ids.texts([scoring.words_of((t or "").encode())])[0][0]) for i, t in given}
    assert sum(r.score for r in real) > 0.8 * sum(lengths[r.doc_id] for r in real) * -math.log10(50_000)
    assert scoring.score(frame.limit(0), standard_ranks()).count() == 0
    held = frame.where(F.expr("crc32(cast(doc_id as string)) % 7 = 2"))
    assert {(r.train_tokens, r.n_known) for r in scoring.score(held, standard_ranks()).collect()} == {(0, 0)}


def test_windows_are_those_of_the_whole_text(monkeypatch):
    """With every run chosen, the runs' targets are the text's ids, each once, with the ids before them as context."""
    ids = scoring.Ids(scoring.read_vocabulary(standard_ranks()))
    for n in (0, 1, 63, 64, 65, 300):
        words = [b"w%dx" % i for i in range(n)]
        text = ids.texts([words])[0][0]
        spans = scoring.spans_of(words, np.arange(max(1, -(-n // scoring.RUN))), ids)
        targets = spans[:, scoring.BLOCK + 1 :].ravel()
        assert (targets[targets >= 0] == text).all()
        before = np.concatenate([np.full(scoring.BLOCK, -1), [ids.end], text])
        at = 0
        for span in spans:
            size = (span[scoring.BLOCK + 1 :] >= 0).sum()
            assert (span[: scoring.BLOCK + 1] == before[at : at + scoring.BLOCK + 1]).all()
            at += size


def test_training_cuts_windows_where_scoring_does():
    """Runs of a text no longer break windows: contexts and targets are the blocks that scoring lays out."""
    ids = scoring.Ids(scoring.read_vocabulary(standard_ranks()))
    texts = [None, b"", b"one", b" ".join(b"w%dx" % i for i in range(700)), b"again " * 130]
    spans = scoring.windows_of(texts, ids)
    known = ids.texts([scoring.words_of(t) for t in texts])[0]
    blocks, targets, alone = scoring.layout(known, ids.end)
    real = (targets >= 0).any(axis=1)
    assert (spans[:, scoring.BLOCK + 1 :] == targets[real]).all() and len(spans) == real.sum()
    assert ((spans[:, 0] < 0) == alone[real]).all()
    inputs = np.where(spans[:, scoring.BLOCK : -1] < 0, ids.end, spans[:, scoring.BLOCK : -1])
    assert (inputs == blocks[1:][real]).all()
    later = ~alone[real]
    assert (spans[later, : scoring.BLOCK] == blocks[:-1][real][later]).all()


def toy(size=58):
    model = scoring.Model(np.arange(1, size + 2), end=size)
    rng = np.random.default_rng(0)
    for p in model.p.values():
        p += rng.normal(0, 0.3, p.shape).astype(np.float32)
    model.p["node"][-1], model.p["bias"][-1] = 0, 30
    model.ready()
    return model, rng


def each(model, text):
    """log10 probability of each id of one text."""
    blocks, targets, alone = scoring.layout([text], model.end)
    return model.log10(blocks, targets, alone)[: len(text)]


def test_scores_are_causal_and_sum_to_one():
    model, rng = toy()
    text = rng.integers(0, 58, 45).astype(np.int32)
    whole, other = each(model, np.append(text, 58).astype(np.int32)), text.copy()
    other[30:] = (other[30:] + 7) % 58
    changed = each(model, np.append(other, 58).astype(np.int32))
    assert np.allclose(whole[:30], changed[:30], atol=1e-5) and not np.allclose(whole[30:], changed[30:])
    for at in (0, 7, 8, 30):  # every id that could follow
        total = sum(10 ** each(model, np.append(text[:at], x).astype(np.int32))[at] for x in range(59))
        assert abs(total - 1) < 1e-4
    texts = [text[:20], text[:9], text, text[:8], text[:1]]
    together = scoring.log10_of(model, texts)
    assert np.allclose(together, [each(model, t).sum() for t in texts], atol=1e-4)


def test_probabilities_of_all_texts_sum_to_one_at_most():
    model, _ = toy(2)
    total, level = 0.0, [np.empty(0, np.int32)]
    for _ in range(12):
        total += (10.0 ** scoring.log10_of(model, [np.append(t, 2).astype(np.int32) for t in level])).sum()
        level = [np.append(t, x).astype(np.int32) for t in level for x in (0, 1)]
    rest = sum(10.0 ** each(model, t).sum() for t in level[:: len(level) // 64]) * (len(level) // 64)
    assert 0.2 < total <= 1 + 1e-6 and rest >= 0


def test_long_codes_keep_their_odds():
    counts = np.array([2**i for i in range(14)])
    nodes, signs, deep, bias = scoring.code_tree(counts, 4)
    p = 1 / (1 + np.exp(-bias[nodes] * signs))
    assert np.allclose(p.prod(axis=1) * 10**deep, (counts + 1) / (counts + 1).sum(), rtol=1e-4)


def test_groups_hold_the_nodes_of_all_their_codes():
    """A vector meets the nodes of its id's group alone, a part of all, and none of its code is missing."""
    counts = np.random.default_rng(3).zipf(1.3, 3000) % 10_000
    nodes, signs, _, bias = scoring.code_tree(counts, scoring.DEPTH)
    tree = scoring.Tree(nodes, signs, len(bias) - 1)
    assert len(tree.columns) > 4 and tree.width < len(bias) / 4
    y = np.random.default_rng(4).integers(0, 3000, (3, 200))
    order, borders, dealt, at = tree.deal(y)
    for i in range(3):
        assert (y[i][order[i]] == dealt[i]).all() and (np.sort(order[i]) == np.arange(200)).all()
        for g, (lo, hi) in enumerate(zip(borders[i], borders[i][1:])):
            own = at[i, lo:hi] - np.arange(lo, hi)[:, None] * tree.width
            assert (tree.columns[g][own] == nodes[dealt[i, lo:hi]]).all()


def windows_for(model, rng, n):
    texts = [np.append(rng.integers(0, model.end, k), model.end).astype(np.int32) for k in rng.integers(0, 40, n)]
    return texts, scoring.windows_of_ids(texts, model.end)


def test_a_step_follows_the_slope_of_the_score():
    """What a step adds to the sums of squares is the slope of the score, told from scores nearby."""
    model, rng = toy()
    model.p["b1"][0] = np.where(np.arange(scoring.HIDDEN) % 2, 4, -4)  # far from where the layer bends
    model.p["w2"] *= 0.1
    texts, spans = windows_for(model, rng, 12)
    assert len(spans) <= scoring.BATCH
    n = sum(map(len, texts))
    loss = lambda: (model.ready(), -scoring.log10_of(model, texts).sum() * math.log(10) / n)[1]
    before, given = {k: v.copy() for k, v in model.sums.items()}, {k: v.copy() for k, v in model.p.items()}
    slopes = {}
    for name, p in model.p.items():
        slopes[name] = []
        for at in rng.integers(0, p.size, 12).tolist():
            if name in ("node", "bias") and at // p.shape[1] == len(p) - 1:
                continue  # never learns
            kept, both = p.ravel()[at], []
            for by in (0.01, -0.01):
                p.ravel()[at] = kept + by
                both.append(loss())
            p.ravel()[at] = kept
            slopes[name].append((at, (both[0] - both[1]) / 0.02))
    told = model.train(spans, 1)
    for name, held in slopes.items():
        for at, slope in held:
            square = (model.sums[name] - before[name]).ravel()[at]
            assert abs(math.sqrt(max(0, square)) - abs(slope)) < 2e-3 + 0.03 * abs(slope), (name, at)
            if abs(slope) > 1e-3:
                assert (model.p[name].ravel()[at] < given[name].ravel()[at]) == (slope > 0)
        assert (told[name][1] == 1).all()
    assert set(told["e"][0].tolist()) == set(np.where(spans[:, :-1] < 0, model.end, spans[:, :-1]).ravel().tolist())


def test_training_beats_the_untrained_model(spark):
    rng = np.random.default_rng(1)
    texts = [np.append(np.tile([1, 2, 3, 4], 10)[: rng.integers(8, 40)], 9).astype(np.int32) for _ in range(200)]
    fresh = lambda: scoring.Model(np.bincount(np.concatenate(texts), minlength=10), end=9)
    spans = []
    for t in texts:
        row = np.concatenate([np.full(scoring.BLOCK, -1), [9], t, np.full(-len(t) % scoring.BLOCK, -1)]).astype(np.int32)
        spans += list(np.lib.stride_tricks.sliding_window_view(row, scoring.SPAN)[:: scoring.BLOCK])
    model = fresh()
    model.ready()
    before = scoring.log10_of(model, texts).sum()
    for _ in range(3):
        model.train(np.array(spans), 1)
    model.ready()
    assert scoring.log10_of(model, texts).sum() > before * 0.5
    # the same in rounds of tasks, whose weights are averaged
    rows = [(i * 2654435761 % 1000003, s.tobytes()) for i, s in enumerate(spans * 4)]
    dealt = fresh()
    scoring.fit(spark.createDataFrame(rows, "pick long, span binary").repartition(5), dealt)
    dealt.ready()
    assert scoring.log10_of(dealt, texts).sum() > before * 0.6


def test_every_id_of_every_training_text_is_trained_on(spark):
    """No run is left out, and texts dealt to tasks teach what their windows teach."""
    ids = scoring.Ids(scoring.read_vocabulary(standard_ranks()))
    texts = [None, b"", b"one", b" ".join(b"w%d" % i for i in range(1000)), b"again " * 130]
    targets = scoring.windows_of(texts, ids)[:, scoring.BLOCK + 1 :].ravel()
    assert (targets[targets >= 0] == np.concatenate(ids.texts([scoring.words_of(t) for t in texts])[0])).all()

    seen = spark.sparkContext.accumulator(0)

    def cut(held):
        seen.add(len(held))
        return scoring.windows_of(held, scoring.Ids(source.value))

    source = spark.sparkContext.broadcast(scoring.read_vocabulary(standard_ranks()))
    docs = spark.createDataFrame([(i if i else None, None if t is None else t.decode()) for i, t in enumerate(texts * 5)], "id long, text string").repartition(3)
    model = scoring.Model(np.ones(ids.end + 1, np.int64), ids.end)
    before = model.p["e"].copy()
    scoring.fit(scoring.dealt_texts(docs), model, cut, 1000)
    assert seen.value == 25
    assert (before != model.p["e"]).any(axis=1).sum() >= len(np.unique(targets[targets >= 0])) * 0.9


def test_parts_are_dealt_evenly_whatever_their_number(spark):
    """With doubles, an even number of parts left most of them empty and the others large."""
    docs = spark.range(3600).select("id", F.col("id").cast("string").alias("text"))
    for parts in (35, 36, 64):
        n = [r["count"] for r in scoring.dealt_parts(scoring.dealt_texts(docs), parts).groupBy("part").count().collect()]
        assert len(n) == parts and sum(n) == 3600 and max(n) < 3 * 3600 / parts
