"""Training-data pipeline: quality, toxicity, near duplicates, secrets, packing.

Each stage takes the documents that its predecessor kept and returns a frame,
which is written as Parquet and read again as the next one's documents.

Defined results: null and empty texts are judged like texts without words and
keep what columns they have; rows with a null id are kept by the join; of rows
that repeat an id and a text one is kept; rows that repeat an id with texts that
don't link all stay; empty tables give no rows; extra columns of ``documents``
come along up to packing, which ignores them whatever their names.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from walkembed.llm import ngram_join, packing, quality_nbsvm, secrets, toxicity
from walkembed.llm.runtime import ensure_checkpoint_dir, read_table, remove_folder


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier, fitted on the table's labelled rows, doesn't reject."""
    model = quality_nbsvm.fit(*quality_nbsvm.labelled_sample(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"), "quality", quality_nbsvm.MAX_TRAIN_ROWS, (4, 2)))
    return quality_nbsvm.keep(docs, model)


def toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity stays below the threshold."""
    lexicon = toxicity.fit(*toxicity.labelled_sample(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"), "toxic", toxicity.MAX_TRAIN_ROWS, (3, 1)))
    return toxicity.keep(docs, lexicon)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group: the one with the smallest id."""
    return ngram_join.distinct_documents(docs)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets blanked."""
    return secrets.redact(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences, with their ids."""
    return packing.pack(docs, emit_ids=True)


STAGES = [
    ("quality classifier", quality),
    ("toxicity", toxic),
    ("n-gram Jaccard join", near_duplicates),
    ("secret scans", secret_scan),
    ("packing", pack),
]

ORACLE_SQL = None  # the classifiers and the tokenizer are beyond SQL; tests hold the run against a brute-force version


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``.

    Each stage's table lies in the shared checkpoint folder until the next one is
    written; the last one stays for the caller.
    """
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/pipeline-{uuid.uuid4().hex}"
    docs = read_table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            remove_folder(spark, f"{folder}/{k - 1}")
    return docs
