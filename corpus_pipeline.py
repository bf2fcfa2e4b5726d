"""From raw documents to packed training sequences, in five stages.

Each stage gets all rows that the one before kept, as a Parquet table, and returns rows of the same
columns; the last returns the pieces of the packed sequences.  Columns beside those of ``documents``
pass through the first four stages.  Null and empty texts fall to the quality rules; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seedrank.llm import decontam, neardup, packing, quality, secrets
from seedrank.llm.common import n_written, release, table, written


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects."""
    return quality.good_documents(docs)


def keep_first_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates."""
    return neardup.deduplicate(docs)


def keep_uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a window of a benchmark item."""
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with a mask in place of each secret found."""
    return secrets.redact(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents, each with its place in a sequence."""
    return packing.pack_documents(docs)


STAGES = [
    ("quality rules", keep_good),
    ("near duplicates", keep_first_copies),
    ("decontamination", keep_uncontaminated),
    ("secrets", mask_secrets),
    ("packing", pack_sequences),
]

#: Near-duplicate classes and tokenisation have no SQL form; tests hold ``run`` against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), n_written(spark)
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    done = n_written(spark) - before
    out = STAGES[-1][1](spark, docs, sf_dir)
    release(spark, done, start=before)  # the result reads tables of its own stage only
    return out
