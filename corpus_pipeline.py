"""Corpus pipeline: quality rules, near duplicates, personal data, source mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns the columns of documents, but
for the last, whose rows are the packed pieces. A stage reads all that the one
before it kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from roadtraj.llm import jaccard, mixing, packing, privacy, quality
from roadtraj.llm.queries import tokenizer_path
from roadtraj.llm.scratch import materialize, release


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the threshold table."""
    return quality.keep(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by five-word shingles at 0.8 or more."""
    return jaccard.keep_one(docs, n=5, percent=80)


def hide_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data and the terms that disclose it replaced or removed."""
    return privacy.sanitise(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated so that each source gets its share of words."""
    return mixing.apply_mix(docs)


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of tokenised documents in windows."""
    return packing.pack(docs, tokenizer_path())


STAGES = [
    ("quality_rules", keep_quality),
    ("ngram_jaccard_join", drop_near_copies),
    ("disclosure_privacy", hide_personal_data),
    ("pivotal_mixing", mix_sources),
    ("sum_of_squares_packing", pack_windows),
]

# Privacy, dependent rounding and packing have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    was = None
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
        if was is not None:
            release(was)
        was = docs
    return STAGES[-1][1](spark, docs, sf_dir)
