"""Queries of the text operators, by the names the driver looks for, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from graphloop.llm import byte_bpe, fingerprint, kneser_ney, language_id, line_dedup, mixing, near_dup, quality_rules, suffix_dedup, url_filter
from graphloop.llm.oracles import SQL
from graphloop.llm.text import table

Query = Callable[[SparkSession, str], DataFrame]

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
URL_RULES = [
    url_filter.UrlRule("block", "com", "/en/"),
    url_filter.UrlRule("allow", "example.com", "/en/7"),
    url_filter.UrlRule("allow", "net", "/de/"),
    url_filter.UrlRule("block", "example.net", "/de/8"),
    url_filter.UrlRule("block", "org", "/es/"),
]


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text")
    return byte_bpe.digest(documents, public_tokenizers.path(VOCABULARY))


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.digest(mixing.mix(table(spark, sf_dir, "documents")))


def op3_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.digest(fingerprint.compare_with_edits(table(spark, sf_dir, "documents")))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.digest(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text")
    return near_dup.digest(near_dup.near_duplicates(documents, width=3, percent=85))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return kneser_ney.digest(documents, table(spark, sf_dir, "labels"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return url_filter.filter_urls(pages, URL_RULES).drop("url")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.digest(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))


def op9_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text")
    return suffix_dedup.digest(suffix_dedup.dedup_passages(documents))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.digest(line_dedup.dedup_lines(documents))


def queries() -> dict[str, Query]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
