"""A cleaning pipeline over `documents`; each stage works on all that its predecessor kept.

Stages are functions (spark, docs, sf_dir) that return the columns of `docs`, but for the last,
which returns the encoding of every document left. Nulls: a null text is rejected by the first
stage; rows with a null id pass the deduplicating stages whole. Extra columns are carried along
until the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spanwalk.llm import bpe, decontamination, langid, line_dedup, simhash
from spanwalk.llm.common import read, store


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts that language identification rejects go."""
    return langid.accepted_documents(docs)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document holds go; n_chars follows the text."""
    return line_dedup.rewrite(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, that of the smallest id."""
    return simhash.keep_one_of_each_group(docs)


def drop_leaked_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of a benchmark item go."""
    return decontamination.clean_documents(docs, read(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.digest(bpe.encode_documents(docs))


STAGES = [
    ("language_id", keep_known_languages),
    ("line_dedup", drop_repeated_lines),
    ("simhash_near_dedup", drop_near_copies),
    ("decontamination", drop_leaked_benchmarks),
    ("bpe", encode),
]
#: Language identification, fingerprints and encoding have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = store(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
