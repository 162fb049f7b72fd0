"""Corpus pipeline: five operators of ``weft.llm`` one after another over ``documents``.

Each stage gets what its predecessor kept, as a written table, and returns the columns of
``documents`` (the last one: ids and decoded texts).  ``n_chars`` follows changed texts.

All stages take null and empty texts, null ids, repeated rows, empty tables and extra columns of any
name, which stay as they are: a row without text is never dropped or changed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weft.llm import bpe, decontamination, minhash, repeats, toxicity
from weft.llm.shared import Workspace, sift, table


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose doc_id isn't in ``gone``; columns of ``docs`` may have any names."""
    ids = Workspace(docs.sparkSession, "gone").keep(gone.select(F.col("doc_id").alias("gone")).distinct(), "ids")
    some, others = sift(docs, "doc_id", ids)
    some = some.alias("left side").join(ids.alias("right side"), F.col("`left side`.doc_id") == F.col("`right side`.gone"), "left_anti")
    return some.union(others)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below 0.5; rows keep all their columns.

    The classifier learns from the labelled rows of the table ``documents``.  Rows with null or empty
    texts or without words score 0 and stay; of repeated rows all stay or all go; a score of 0.5 goes.
    """
    given = table(spark, sf_dir, "documents", "doc_id", "text")
    network = toxicity.fit(given, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.keep_clean(docs, network)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that with the smallest id, of each group of near copies (five-word shingles, 0.8).

    Rows without words or without an id belong to no group and stay; rows that repeat an id stay or go
    together.
    """
    judged = minhash.near_duplicates(docs, name="stage-near")
    return _without(docs, judged.where("doc_id is not null and not kept"))


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without passages of 50 words and more that a document with a smaller id has.

    Null texts and rows without an id stay as they are; a text that is all such passages becomes empty;
    rows that repeat an id are one document and are cut alike.
    """
    runs = Workspace(spark, "stage-runs").keep(repeats.find(docs, name="stage-repeats"), "runs")  # read more than once
    cut = repeats.remove(docs, runs)
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(dict(docs.dtypes)["n_chars"])))
    return cut


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item (no window of an item's size with a similarity of 0.8).

    Null and empty texts and rows without an id match nothing and stay; rows that repeat an id go when
    one of them matches.  An empty benchmark: all stay.
    """
    return _without(docs, decontamination.matches(docs, table(spark, sf_dir, "benchmark", "item_id", "text"), name="stage-leaks"))


def to_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids, decoded) of every document; null and empty texts have no ids and decode to the empty text."""
    return bpe.encode(docs, bpe.standard_vocabulary())


STAGES = [
    ("toxicity", drop_toxic),
    ("near_copies", drop_near_copies),
    ("repeats", cut_repeats),
    ("leaks", drop_leaks),
    ("tokens", to_tokens),
]

#: Trained models and tokenizers are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table ``documents``; each stage's result is written and read again."""
    work, before = Workspace(spark, "pipeline"), None
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        opened = len(Workspace.open)
        docs = work.keep(stage(spark, docs, sf_dir), name)
        Workspace.close(opened)  # the stage's own tables
        if before is not None:
            work.drop(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
