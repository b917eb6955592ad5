"""A pipeline that prepares documents for training, as stages over tables.

Each stage reads what its predecessor wrote.  All but the last keep the columns
of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from bundlery.llm.benchmark_leaks import drop_leaks
from bundlery.llm.bin_packing import pack_documents
from bundlery.llm.language_id import keep_identified
from bundlery.llm.lineage import remove_folder, shared_folder
from bundlery.llm.personal_data import sanitise
from bundlery.llm.queries import table, vocabulary
from bundlery.llm.signature_join import drop_near_duplicates


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without text, letters or a recognised language go."""
    return keep_identified(docs)


def join_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays (5 words, Jaccard 0.8)."""
    return drop_near_duplicates(docs, width=5, num=80, den=100)


def remove_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that contain a benchmark item go."""
    return drop_leaks(docs, table(spark, sf_dir, "benchmark"), share=0.8, width=5)


def sanitise_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Identifiers and the terms that disclose them are replaced by tags."""
    return sanitise(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of the documents with their sequences and offsets."""
    return pack_documents(docs, vocabulary("word_bpe_49k.json"), capacity=2048)


STAGES = [
    ("language_id", identify_language),
    ("ngram_jaccard_join", join_near_duplicates),
    ("benchmark_decontamination", remove_benchmark_leaks),
    ("personal_data", sanitise_personal_data),
    ("best_fit_packing", pack_sequences),
]

#: Learning, trees and packing are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order over ``documents``; each result is written and read again.

    A stage's result is removed from the shared folder once the next one is written.
    """
    docs, done = table(spark, sf_dir, "documents"), None
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        path = f"{folder}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        if done:
            remove_folder(spark, done)
        docs, done = spark.read.parquet(path), path
    return STAGES[-1][1](spark, docs, sf_dir)
