"""Bounded samples of labelled documents for the two classifiers, and their common outputs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import held_out

#: Rows whose crc32(doc_id as text) mod FOLDS is 0 are held out: no label of theirs is read.
FOLDS = 5


def usable_labels(labels: DataFrame, label: str) -> DataFrame:
    """(doc_id, y) of the labels that may be learned from."""
    usable = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & ~held_out(FOLDS, 0))
    return usable.groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))


def sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int) -> DataFrame:
    """(doc_id, text, y) of up to ``per_class`` labelled rows of each class that aren't held out.

    The rows with the least hash of doc_id are taken, whatever the order and partitions of the
    tables.  Only ids and labels are sorted; the chosen ids (2 * ``per_class`` at most, so a
    broadcast of bounded size) then meet the documents.  Null ids and labels other than 0 and 1 are
    passed over; of an id with several labels the greatest counts, of a repeated document each row.
    """
    usable = usable_labels(labels, label)
    parts = [usable.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for y in (0, 1)]
    return docs.select("doc_id", "text").join(F.broadcast(parts[0].union(parts[1])), "doc_id")


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -60, 60)))


def judged(scored: DataFrame, threshold: float) -> DataFrame:
    """Adds held_out and predicted to (doc_id, score, ...)."""
    first = [F.col("doc_id"), held_out(FOLDS, 0).alias("held_out"), F.col("score"), (F.col("score") >= threshold).cast("int").alias("predicted")]
    return scored.select(*first, *[c for c in scored.columns if c not in ("doc_id", "score")])
