"""A corpus pipeline: documents in, packed training sequences out.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept and
gives a DataFrame, which is written as Parquet and read again as the next one's docs.
All stages but the last give the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from rpqspark.llm import common, packing, quality, secrets, simhash, suffixes


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier keeps, with all their columns.

    Null text is scored like empty text; unknown or null languages, sources and sizes count as
    seen in no fit; repeated rows are scored alike; an empty table, or one
    without labels, loses nothing.
    """
    return quality.kept(docs, common.read(spark, sf_dir, "labels"))


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: five-word shingles, similarity 0.8.

    The smallest doc_id stays, null ids come last; repeated rows leave one; texts without
    words (null, empty, blank) are one group; rows that share an id but are not alike all stay.
    """
    return simhash.one_of_each(docs)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages (250 bytes or more, about fifty words) that occur elsewhere.

    Null text stays null, empty text empty; every row stays, also one that loses all its text;
    rows that are still repeated are places of their own.
    """
    return suffixes.without_repeats(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with secrets masked.

    Null text stays null; repeated rows are masked alike; every row stays.
    """
    return secrets.redact(docs)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of all documents and their places in sequences.

    Null text is empty; every row has a piece at least; repeated rows are packed as rows of
    their own; an empty table gives no sequences.
    """
    return packing.best_fit(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality classifier", good_documents),
    ("simhash near-dedup", distinct_documents),
    ("suffix-array dedup", without_repeats),
    ("secret scans", without_secrets),
    ("best-fit packing", sequences),
]

#: SQL can express neither the classifier nor the fingerprints; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over documents."""
    docs, stage = common.read(spark, sf_dir, "documents"), common.Stage(spark, "pipeline")
    for k, (_, f) in enumerate(STAGES):
        docs = f(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stage.save(docs, f"stage{k}")
    return docs
