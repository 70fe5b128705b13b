"""A corpus pipeline: quality rules, near-duplicates, decontamination, secrets, and a mix of the sources.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return
the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from multiscale_scatter.llm import decontamination, mixing, near_duplicates, quality_rules, secret_scan
from multiscale_scatter.llm.shared import discard, materialize, scratch


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the rules, of hosts that do."""
    return quality_rules.keep_good(docs)


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (five-word shingles, similarity 0.8)."""
    return near_duplicates.drop_near_duplicates(docs, width=5, percent=80)


def clean_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without benchmark items."""
    return decontamination.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def redacted_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets replaced by a mark."""
    return secret_scan.redact(docs)


def mixed_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What the mix takes of each document: doc_id, source, size, source_size, target, taken."""
    return mixing.taken(mixing.mix(docs))


STAGES = [
    ("quality rules", good_documents),
    ("near duplicates", distinct_documents),
    ("decontamination", clean_documents),
    ("secret scan", redacted_documents),
    ("mixing", mixed_documents),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        if k == len(STAGES) - 1:
            return stage(spark, docs, sf_dir)
        # what a stage writes on its way goes with it, and so does its input
        with scratch(spark):
            before, docs = docs, materialize(stage(spark, docs, sf_dir), f"stage-{k + 1}", outside=True)
        discard(before)


#: Signatures and permutations are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None
