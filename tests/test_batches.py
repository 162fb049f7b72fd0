"""Relations counted batch by batch, draws in numpy, and words read together: the same results as the plain ways."""

import hashlib
import random

import pyarrow as pa
import pytest

from weft.operators import baselines, measures, precedence
from weft.operators.dag import PrecedenceGraph
from weft.plans import learn
from weft.sources.draws import Draws

ODD = [("e", "1", ["b", "a", "b"]), ("e", "2", []), ("e", "3", ["a", "c"]), ("f", "4", []), (None, "5", ["x", "y"]), ("g", "6", ["p", None, "q", "p"]), ("h", "7", None), ("h", "8", ["é", "z", "é"]), ("i", "9", [None])]


def rows(frame):
    return sorted(map(str, frame.select(sorted(frame.columns)).collect()))


@pytest.mark.parametrize("operator", [precedence.pairs, precedence.multiplicities, measures.conflict_density, baselines.multiplicities_only])
def test_batches_equal_signatures_on_odd_words(spark, operator):
    words = spark.createDataFrame(ODD, "element string, word_id string, symbols array<string>")
    assert rows(operator(words)) == rows(operator(words, plan="batches"))


@pytest.mark.parametrize("operator", [learn.relations, precedence.adjacency, baselines.ordered_chain, learn.collapsed])
def test_batches_equal_signatures(spark, operator):
    words = spark.createDataFrame([r for r in ODD if r[0] and r[2] is not None and None not in r[2]] + [("e", "10", list("aabbac"))], "element string, word_id string, symbols array<string>")
    assert rows(operator(words)) == rows(operator(words, plan="batches"))


def test_draws_are_md5():
    keys = ["", "7", "123456", "ü" * 40, "a" * 46, "a" * 47, "x" * 130]
    assert list(Draws(pa.array(keys))("article/12")) == [int(hashlib.md5(f"{k}/article/12".encode()).hexdigest()[:7], 16) % 1000 / 1000.0 for k in keys]


def test_words_read_together_change_the_graph_as_one_by_one():
    draw = random.Random(1)
    for _ in range(300):
        words = [sorted(w) if draw.random() < 0.6 else w for w in ([draw.choice("abcdefg") for _ in range(draw.randint(0, 8))] for _ in range(draw.randint(0, 60)))]
        one, all_ = PrecedenceGraph(), PrecedenceGraph()
        assert [i for i, w in enumerate(words) if one.absorb(w)] == all_.absorb_all(pa.array(words, pa.list_(pa.string())))
        assert (one.edges(), one.splits) == (all_.edges(), all_.splits)
