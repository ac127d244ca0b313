"""The corpus pipeline: quality classifier, exact dedup, near-dedup, secret redaction, packing.

Each stage reads what its predecessor wrote, so its input is a plain scan of files. All but the last return the
columns of documents; the last returns the pieces of the packed sequences. Before a stage is planned the executors give back
what the one before has left in their heaps, since all stages run in the same ones.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tmotif.llm import exact, packing, quality, secrets, simhash
from tmotif.llm.common import executors_give_back, staged
from tmotif.llm.queries import vocabulary


def keep_good_text(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    executors_give_back(spark)
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the smallest doc_id stays."""
    executors_give_back(spark)
    return exact.drop_exact_copies(docs, stable=True)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays, over five-word shingles."""
    executors_give_back(spark)
    return simhash.drop_near_copies(docs, stable=True)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets in the text give way to the names of their kinds."""
    executors_give_back(spark)
    return secrets.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 2048 tokens."""
    executors_give_back(spark)
    return packing.pack_documents(docs, vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("quality_classifier", keep_good_text),
    ("exact_dedup", drop_exact_copies),
    ("near_dedup", drop_near_copies),
    ("secret_scan", redact_secrets),
    ("packing", pack),
]

#: Perplexities, components and token ids are beyond SQL; the tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = staged(docs, "stage")
    return docs
