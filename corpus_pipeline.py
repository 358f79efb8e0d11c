"""Corpus pipeline: five operators one after the other over whole documents.

A stage takes (spark, docs, sf_dir) and gives the rows that go on, with all columns of `documents`; the last gives
packed pieces. Rows are written between stages, so that each stage starts from files.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from adapterlab.llm.common import shared_folder, table
from adapterlab.llm.decontaminate import drop_leaked
from adapterlab.llm.packing import pack_documents
from adapterlab.llm.quality import fit_quality, keep_quality
from adapterlab.llm.queries import tokenizer_file
from adapterlab.llm.shingles import keep_one_of_similar
from adapterlab.llm.suffixes import remove_repeats


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    return keep_quality(docs, fit_quality(docs, table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays; five-word shingles with a similarity of 0.8 or more link two documents.

    Fingerprints within three bits are candidates, found by multi-index hashing; what they miss is found by shingles.
    """
    return keep_one_of_similar(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes that came earlier are cut out of the texts; every document stays."""
    return remove_repeats(docs)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return drop_leaked(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, tokenizer_file())


STAGES = [
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("benchmark_leaks", benchmark_leaks),
    ("packing", packing),
]
ORACLE_SQL = None  # trees and packing have no SQL form; tests compare the stages with brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_folder(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
