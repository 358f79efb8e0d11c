"""Queries and SQL of the training-data operators, for the entry module."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from adapterlab.llm.chat import CHAT_SQL, rotate_perspectives
from adapterlab.llm.common import table
from adapterlab.llm.decontaminate import find_leaks
from adapterlab.llm.html import extract_main_text
from adapterlab.llm.packing import pack_documents
from adapterlab.llm.quality import fit_quality, score_quality
from adapterlab.llm.simhash import near_duplicates
from adapterlab.llm.suffixes import repeated_bytes
from adapterlab.llm.topk import TOPK_SQL, top_k
from adapterlab.llm.toxicity import fit_toxicity, score_toxicity
from adapterlab.llm.urls import URL_SQL, filter_urls, task_rules


def op1_perspective_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rotate_perspectives(table(spark, sf_dir, "conversations"))


def op2_quality_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return score_quality(documents, fit_quality(documents, table(spark, sf_dir, "labels")))


def op3_suffix_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_bytes(table(spark, sf_dir, "documents"))


def tokenizer_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), tokenizer_file())


def op5_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_toxicity_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return score_toxicity(documents, fit_toxicity(documents, table(spark, sf_dir, "labels")))


def op7_pivot_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings"))


def op8_tag_path_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"), task_rules(spark))


def op10_simhash_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_perspective_rotation, op2_quality_trees, op3_suffix_buckets, op4_best_fit_packing, op5_template_decontamination,
        op6_toxicity_ngrams, op7_pivot_topk, op8_tag_path_text, op9_url_rules, op10_simhash_multi_index,
    )
}
SQL = {"op1_perspective_rotation": CHAT_SQL, "op7_pivot_topk": TOPK_SQL, "op9_url_rules": URL_SQL}
