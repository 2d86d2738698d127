"""The corpus pipeline: from raw documents to shuffled shards.

Each stage is a function of (spark, docs, sf_dir), where docs is what the stage before kept, and works on all of it:

1. quality classifier: documents that it rejects go.
2. near-duplicate detection: one document of each class stays, that of the least doc_id.
3. benchmark decontamination: documents that hold a benchmark item go.
4. mixing: each document as often as the mix takes it.
5. sharding: all records in shuffled shards, with shard and slot.

All stages but the last return the columns of documents. run() writes and rereads each stage's rows in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from utilmine.llm import decontamination, mixing, near_dedup, quality_classifier, sharding
from utilmine.llm.shared import documents, written
from utilmine.plans.ship import to_workers


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_classifier.without_rejected(docs, to_workers(spark).read.parquet(f"{sf_dir}/labels.parquet"))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    to_workers(spark)
    return near_dedup.without_near_copies(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.without_contaminated(docs, to_workers(spark).read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def sharded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    to_workers(spark)
    return sharding.shards(docs, 40)


STAGES = [
    ("quality classifier", quality),
    ("MinHash near-dedup", near_copies),
    ("benchmark decontamination", decontaminated),
    ("mixing sources to target weights", mixed),
    ("sharding", sharded),
]

#: SQL cannot express the fitted classifier, the sampled bands and the seeded shuffle; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for _, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir))
    return docs
