"""Labelled training rows: the fold rule and bounded, repeatable samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Most labelled rows that a model is fitted on (a documented bound; everything else reads all rows).
TRAIN_ROWS = 20_000


def held_out(doc_id: Column) -> Column:
    """The fifth of the documents whose labels are never learnt from; a null id is held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def training_labels(labels: DataFrame, label: str, rows: int = TRAIN_ROWS) -> DataFrame:
    """At most ``rows`` labelled ids outside the held-out fold, in a seeded hash order: (doc_id, label)."""
    known = labels.select("doc_id", F.col(label).cast("int").alias("label")).where(F.col("label").isNotNull() & ~held_out(F.col("doc_id")))
    return known.orderBy(F.xxhash64("doc_id", F.lit(29)), "doc_id").limit(rows)


def training_documents(docs: DataFrame, labels: DataFrame, label: str, rows: int = TRAIN_ROWS) -> DataFrame:
    """(doc_id, text, label) of the sampled ids; the broadcast holds ``rows`` short rows at most."""
    return docs.select("doc_id", "text").join(F.broadcast(training_labels(labels, label, rows)), "doc_id")
