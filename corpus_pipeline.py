"""A corpus pipeline of five stages: quality, near duplicates, personal data, mix, token ids.

Every stage takes what its predecessor kept, written as Parquet and read again; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpick.llm import mix, neardup, pieces, pseudonym, quality
from evenpick.llm.queries import DEMONSTRATION_KEY, PIECE_MODEL, table
from evenpick.llm.textbits import without
from evenpick.plans.durable import maybe_broadcast, staged

#: Documents that score below this go (as in the quality query).
QUALITY_FLOOR = 0.3
BROADCAST_IDS = 500_000


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality model does not reject, with their own columns whatever these are called.

    Null and empty texts are scored as the empty text and stay or go by that score; very long texts are read whole; repeated rows share a fate;
    without usable labels all score 0.5 and stay; an empty table stays empty.
    """
    model = quality.train_quality(docs, table(spark, sf_dir, "labels"))
    score = f"score_{uuid.uuid4().hex}"
    return without(quality.score_quality(docs, model, score).where(F.col(score) >= QUALITY_FLOOR), score)


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group (five-word shingles, similarity 0.8 or more); documents without an id cannot be grouped and stay.

    Null and empty texts are like nothing and stay; of equal or tied documents the least id stays; rows that share an id share a fate.
    """
    gone = neardup.near_duplicates(docs).where(F.col("doc_id").isNotNull() & ~F.col("kept")).select("doc_id").distinct()
    gone = maybe_broadcast(staged(gone.withColumnRenamed("doc_id", "gone_id"), "gone"), BROADCAST_IDS)
    return docs.join(gone, docs.doc_id == gone.gone_id, "left_anti")


def replace_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data as linkable pseudonyms; lengths are counted anew.

    Null texts stay null (their length too), empty ones empty; every row is kept; texts are read whole; repeated rows repeat; all other
    columns are carried along.
    """
    out = pseudonym.pseudonymise(docs, pseudonym.session_key(spark, DEMONSTRATION_KEY))
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated as often as their source's target asks.

    Null and empty texts have no words: they are taken once per whole epoch of their source, as its other documents are; a null source is a source;
    rows that share id and length share their fate; an empty table stays empty; other columns are carried along.
    """
    return mix.mix_documents(docs)


def to_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per document row of the mix: the number of its token ids and the digests of ids and decoded text.

    Null texts are encoded as empty ones (no ids); texts of any length are encoded whole; every row gives one row.
    """
    return pieces.piece_digest(docs, PIECE_MODEL)


STAGES = [
    ("quality classifier", keep_quality),
    ("MinHash near-dedup", keep_one_of_each_group),
    ("PII", replace_personal_data),
    ("mixing sources to target weights", mix_sources),
    ("SentencePiece encoding and decoding", to_ids),
]

#: The stages learn models, follow sketches and run tokenizers, which SQL cannot express; tests/llm holds every stage against a plain version on small tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = staged(docs, f"stage-{i}")
    return docs
