"""The corpus pipeline: five stages from raw documents to packed training sequences.

Each stage is a function (spark, docs, sf_dir) -> DataFrame over all that its predecessor kept. All but the last return the
columns that came in. ``run`` writes every stage as Parquet to shared storage and rereads it, so a lost executor costs a
stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from headcount.llm.decontamination import decontaminate
from headcount.llm.jaccard_join import drop_near_duplicates
from headcount.llm.packing import pack_documents
from headcount.llm.quality_rules import filter_quality
from headcount.llm.secrets import redact_secrets
from headcount.sources.storage import dealt, stored


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail a rule go."""
    return filter_quality(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays."""
    return drop_near_duplicates(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of the benchmark are cut out; documents that consist mostly of them go."""
    return decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked."""
    return redact_secrets(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their place in a sequence."""
    return pack_documents(docs).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


STAGES = [
    ("quality_rules", quality),
    ("ngram_jaccard_join", near_duplicates),
    ("benchmark_decontamination", decontamination),
    ("secret_scan", secret_scan),
    ("best_fit_packing", packing),
]

#: Tokenising and packing have no SQL form; tests/llm holds the result against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = dealt(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), name)
    return docs
