"""Column layouts of the engine's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: One observed word: the labels of one sequence, in order, under the element it describes.
CORPUS = T.StructType(
    [
        T.StructField("element", T.StringType()),
        T.StructField("word_id", T.StringType()),
        T.StructField("symbols", T.ArrayType(T.StringType())),
    ]
)

#: One row per learned schema; ``factors`` are chains of (symbol, multiplicity).
SCHEMA = (
    "element string, learner string, factors array<array<struct<symbol:string,mult:string>>>, "
    "words long, status string, repaired boolean, text string"
)


def assert_corpus(corpus: DataFrame) -> DataFrame:
    """The corpus itself; fails at run time on a null element, word or symbol, and at once on wrong columns."""
    missing = {"element", "word_id", "symbols"} - set(corpus.columns)
    if missing:
        raise ValueError(f"not a corpus: no column {sorted(missing)}")
    bad = F.col("element").isNull() | F.col("symbols").isNull() | F.exists("symbols", lambda s: s.isNull())
    symbols = F.when(bad, F.raise_error(F.lit("null element, word or symbol in corpus"))).otherwise(F.col("symbols"))
    return corpus.select("element", "word_id", symbols.alias("symbols"))
