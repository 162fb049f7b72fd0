"""BPE encoding and decoding of a text column (see ``pieces`` for the method)."""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame

from .pieces import PrefixEncoder, coder, read_vocabulary
from .shared import parts, table


def encode(docs: DataFrame, vocabulary: str, key: str = "doc_id", text: str = "text", digests: bool = False) -> DataFrame:
    """Ids of every text, and the text decoded from them.

    Returns (key, n_tokens, ids array<int>, decoded), or with ``digests`` (key, n_tokens,
    ids_sha256, decoded_sha256) without moving ids and texts.  ``vocabulary``: path of a tokenizers
    file, read on the driver.  Null and empty texts have no ids and decode to the empty text; rows
    with null or repeated keys stay as they are; other columns are not read.
    """
    source = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))
    kind = dict(docs.dtypes)[key]

    def run(batches):
        own = coder(source, PrefixEncoder)
        for batch in parts(batches):
            n, first, second = [], [], []
            for text in batch.column(1).to_pylist():
                packed = own.packed(text)
                back = own.decoded(packed)
                n.append(len(packed) // 4)
                if digests:
                    first.append(hashlib.sha256(packed).hexdigest())
                    second.append(hashlib.sha256(back.encode()).hexdigest())
                else:
                    first.append(memoryview(packed).cast("I").tolist())
                    second.append(back)
            ids = pa.array(first, pa.string()) if digests else pa.array(first, pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), ids, pa.array(second, pa.string())], names=names)
        own.trim()

    names = [key, "n_tokens", *(("ids_sha256", "decoded_sha256") if digests else ("ids", "decoded"))]
    columns = "ids_sha256 string, decoded_sha256 string" if digests else "ids array<int>, decoded string"
    return docs.select(key, text).mapInArrow(run, f"`{key}` {kind}, n_tokens long, {columns}")


def standard_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op7_bpe(spark, sf_dir: str) -> DataFrame:
    """Digests of ids and decoded text of every document."""
    return encode(table(spark, sf_dir, "documents", "doc_id", "text"), standard_vocabulary(), digests=True)
