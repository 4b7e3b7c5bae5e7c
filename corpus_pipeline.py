"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again by the next.

1. quality: the positive-unlabelled classifier; rejected documents go.
2. lines: exact set-similarity line deduplication; later matches leave the texts.
3. near duplicates: n-gram Jaccard join; one document of each group stays.
4. benchmark: documents with a benchmark passage go.
5. packing: the pieces of the training sequences.

Every stage but the last returns the columns of its input; nulls, repeated rows, and further columns are treated as the
operators' docstrings say. Without checkpoint folder (tests, local mode) intermediate tables go to a private one.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phraseloom.llm import decontamination, jaccard_join, line_dedup, packing, quality_classifier
from phraseloom.llm.common import ensure_checkpoint_dir, table


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_classifier.keep_accepted(docs, quality_classifier.train(docs, table(spark, sf_dir, "labels")))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicate_lines(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_one_per_group(docs)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [("quality classifier", quality), ("line dedup", lines), ("n-gram Jaccard join", near_duplicates), ("benchmark decontamination", benchmark), ("packing", pack)]

#: The classifier and the packing cannot be said in SQL; tests hold every stage against a plain reading.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
