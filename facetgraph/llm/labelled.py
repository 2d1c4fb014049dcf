"""Bounded samples of labelled rows for the classifiers.

A sample is the SAMPLE_ROWS documents of smallest id hash, so it is the same on
every run and its size does not grow with the table; everything scored is scored whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows that a classifier is fitted on, at most.
SAMPLE_ROWS = 12_000


def fold(doc_id: Column, folds: int) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def sample_ids(rows: DataFrame, most: int = SAMPLE_ROWS, seed: int = 7) -> DataFrame:
    return rows.where("doc_id is not null").orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(most)


def training_labels(labels: DataFrame, column: str, folds: int, held_out: int) -> DataFrame:
    """(doc_id, label) of the training folds; null labels are left out, of several for a document the largest counts."""
    known = labels.where(F.col(column).isNotNull() & (fold(F.col("doc_id"), folds) != held_out))
    return known.groupBy("doc_id").agg(F.max(F.col(column).cast("int")).alias("label"))


def texts_of(documents: DataFrame, sample: DataFrame) -> DataFrame:
    """The sample with its texts, one for each row of it however often a doc_id is repeated: the least. The sample is broadcast, being SAMPLE_ROWS rows a class at most."""
    own = [c for c in sample.columns if c != "doc_id"]
    found = documents.select("doc_id", F.col("text").cast("string")).join(F.broadcast(sample), "doc_id")
    return found.groupBy("doc_id", *own).agg(F.min("text").alias("text"))
