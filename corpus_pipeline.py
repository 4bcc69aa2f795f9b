"""Corpus pipeline: language ID, near-duplicate removal, sanitisation, mixing, encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written
as Parquet and read again as the next stage's ``docs``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from harvestgrid.llm import bpe, langid_crf, mixing, pii, similar
from harvestgrid.llm.common import TEXT_ROWS, spool, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has a language; lang becomes the predicted one."""
    return langid_crf.keep_identified(docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of texts with a five-word Jaccard similarity of 0.8 or more, that of the smallest id."""
    return similar.keep_first(docs)


def sanitise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with personal data and the terms that disclose it replaced."""
    return pii.sanitise(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows repeated or left out so that the sources meet their target weights."""
    return mixing.take_copies(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the encoded and of the decoded texts."""
    # The digests are small and written here, so that the texts go to Python in small batches.
    return spool(bpe.round_trip(docs), "coded", rows=TEXT_ROWS)


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("pii", sanitise),
    ("mix", mix),
    ("bpe", encode),
]

#: Language ID and encoding have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = spool(stage(spark, docs, sf_dir), name)
    return spool(STAGES[-1][1](spark, docs, sf_dir), STAGES[-1][0])
