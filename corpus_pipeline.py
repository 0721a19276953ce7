"""The training-data pipeline: five operators, each written out before the next reads it.

Defined cases, for every stage: rows are judged one by one, whatever ids they share, so a
row is never lost for another's fault; null and empty texts have too few words and go in
the first stage (given alone to later ones they are one group, hold no item, have no spans
and pack as the end token); rows repeated as a whole count each time in the rules, and one
of them stays after the second stage; null ids come last among near copies and are kept
otherwise; very long texts are held by one task at a time; an empty table stays empty;
other columns pass through the first four stages, whatever their names. Filters keep whole
rows; masking changes ``text`` and ``n_chars`` only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from glyphfold.llm import bin_packing, decontaminate, pii_crf, quality_rules, simhash_dedup
from glyphfold.session import settle


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules and their host's verdict keep."""
    return quality_rules.quality_filter(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the smallest id, of every group of near-duplicates."""
    return simhash_dedup.near_dedup(docs)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data masked."""
    return pii_crf.redact(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in training sequences."""
    return bin_packing.pack(docs, *bin_packing.public_paths())


STAGES = [
    ("quality_rules", quality),
    ("simhash_near_dedup", near_duplicates),
    ("benchmark_decontamination", benchmark),
    ("personal_data", personal_data),
    ("bin_slack_packing", packing),
]

#: SQL can't express fingerprints, random fields or packing; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
