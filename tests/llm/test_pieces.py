import random

import public_tokenizers
import pytest
from tokenizers import Tokenizer

from weft.llm.pieces import Coder, LibraryEncoder, PrefixEncoder, Vocabulary, read_vocabulary

PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def vocabulary():
    return Vocabulary(read_vocabulary(PATH))


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def texts():
    rng = random.Random(1)
    letters = "abcdefgh etaoin  \n\t'sdltrev0123.,!?éßñÈöä中文😀̀  \x1c\x00ⅫⅣ²½\U00010940౜_-"
    yield from ["", " ", "  ", "\n", "a", "aaaaaaaaaaaaaaaaaaaa", "<|endoftext|>", "x <|endoftext|><|endoftext|> y", "<|endoftext", "it's we'll I'D", "ab" * 3000, "=" * 500, " 　 x", "\r\n\r\n x"]
    for _ in range(600):
        yield "".join(rng.choice(letters) for _ in range(rng.randrange(60)))
    for _ in range(300):
        yield "".join(chr(rng.choice([rng.randrange(32, 127), rng.randrange(160, 0x600), rng.randrange(0x2000, 0x2400)])) for _ in range(rng.randrange(40)))


@pytest.mark.parametrize("encoder", [PrefixEncoder, LibraryEncoder])
def test_ids_equal_the_library_and_decode_back(vocabulary, library, encoder):
    own = Coder(vocabulary, encoder)
    for text in texts():
        ids = library.encode(text, add_special_tokens=False).ids
        packed = own.packed(text)
        assert list(memoryview(packed).cast("I")) == ids, text
        assert own.decoded(packed) == library.decode(ids, skip_special_tokens=False) == text


def test_every_entry_encodes_to_itself_and_random_bytes_agree(vocabulary, library):
    own = PrefixEncoder(vocabulary)
    rng = random.Random(2)
    entries = [b for b in vocabulary.ids if b]
    for token in rng.sample(entries, 3000):
        n = len(token)
        last = [-1] * (n + 1)
        for end, (length, i) in own.automaton.iter(token.decode("latin-1")):
            if last[end + 1] < 0 and (end + 1 == length or own.compatible(last[end + 1 - length], i)):
                last[end + 1] = i
        assert last[n] == vocabulary.ids[token]
    for _ in range(800):
        word = "".join(rng.choice("thereisanoing") for _ in range(rng.randrange(1, 40)))
        assert own.encode(word.encode()) == library.encode(word, add_special_tokens=False).ids


def test_null_is_empty(vocabulary):
    assert Coder(vocabulary).packed(None) == b""


def test_query_over_documents(spark, library):
    import hashlib
    import struct

    from weft.llm.bpe import encode, op7_bpe

    rows = op7_bpe(spark, "/root/testdata/sf0.001").collect()
    given = {r.doc_id: r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()}
    assert len(rows) == len(given)
    for r in rows:
        ids = library.encode(given[r.doc_id] or "", add_special_tokens=False).ids
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    odd = spark.createDataFrame([(None, None, 1), (1, "", 2), (1, "a b", 3)], "doc_id long, text string, n_tokens int")
    assert sorted((r.n_tokens, r.decoded) for r in encode(odd, PATH).collect()) == [(0, ""), (0, ""), (2, "a b")]
    assert encode(odd.limit(0), PATH).count() == 0


def test_texts_packed_together(vocabulary, library):
    own = Coder(vocabulary, LibraryEncoder)
    many = [*texts(), None]
    for _ in range(2):
        for text, packed in zip(many, own.packed_all(many)):
            assert list(memoryview(packed).cast("I")) == library.encode(text or "", add_special_tokens=False).ids, text
    assert all(len(p) <= 64 for p in own)


def test_sift_loses_no_row_of_an_id(spark):
    """Rows of ids are all among the first, nearly all others among the second, whatever columns are called."""
    from weft.llm.shared import sift

    keys = [None, -5, 2**62, *range(0, 30_000, 3)]
    frame = spark.createDataFrame([(k, i) for i, k in enumerate(keys)], "id long, row long").withColumnRenamed("row", "c0").repartition(3)
    held = {k for k in keys[1:] if k % 5 == 0 or k < 0}
    ids = spark.createDataFrame([(k,) for k in held] + [(None,)], "bits long")
    first, second = (sorted(x.collect(), key=lambda r: r.c0) for x in sift(frame, "id", ids))
    assert sorted(r.c0 for r in first + second) == list(range(len(keys))) and first[0].__fields__ == ["id", "c0"]
    assert held <= {r.id for r in first} and None not in {r.id for r in first}
    assert len(first) < len(held) + len(keys) / 8
    none, all_ = sift(frame, "id", ids.limit(0))
    assert none.count() == 0 and all_.count() == len(keys)
