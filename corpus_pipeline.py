"""A training-data pipeline of five stages over the documents table."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from meshpack.deploy import ship
from meshpack.llm import decontaminate, secret_scan, simhash, sp_sampling, toxicity
from meshpack.llm.common import shared_dir, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject."""
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: the one with the least id."""
    return simhash.keep_first(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold too little of the benchmark to count as contaminated."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets replaced by their kind."""
    return secret_scan.redact(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The sampler's distinct segmentations of every document, with their piece ids, beside its language and source.

    A row for each document: the first segmentation in the columns, the others, for further epochs, in ``more``.

    Small batches: workers of earlier stages still live on the executors, which share their memory.
    """
    return sp_sampling.segmentations(docs, with_ids=True, keep=("doc_id", "lang", "source"), chars=200_000, nested=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("secrets", redact_secrets),
    ("encoding", encode),
]

#: Classifier, fingerprints and sampling have no SQL form; the tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in turn over ``documents``, each stored as Parquet and read again for the next.

    A stage's folder goes once the next one is stored; the last stored one is what the result reads.
    """
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    place = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    before = None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{place}/{name}")
        docs = spark.read.parquet(f"{place}/{name}")
        if before:
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{place}/{before}")
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        before = name
    return STAGES[-1][1](spark, docs, sf_dir)
