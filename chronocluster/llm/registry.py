"""The queries of the text operators, with production parameters, and their SQL where SQL can state them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, html_text, jaccard_join, language_id, secrets, simhash, substring_dedup, token_counts, url_filters
from .common import load

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer(name: str) -> str:
    """Where a public vocabulary file is installed."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(load(spark, sf_dir, "documents"), "doc_id", "text", tokenizer("byte_bpe_50k.tiktoken"))


def op2_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(load(spark, sf_dir, "documents"), ["doc_id"], "text", tokenizer("byte_bpe_50k.json"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.document_fingerprints(load(spark, sf_dir, "documents"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.digest(substring_dedup.deduplicate(load(spark, sf_dir, "documents")))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest(secrets.scan(load(spark, sf_dir, "documents"), ["doc_id"], "text", tokenizer("byte_bpe_50k.json")))


def op6_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.main_texts(load(spark, sf_dir, "pages"), ["page_id", "url"])


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    labelled = language_id.identify(docs, ["doc_id"], "text", language_id.train(docs))
    return labelled.select("doc_id", language_id.held_out("doc_id").alias("held_out"), "lang_pred", "score")


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similarity_components(spark, load(spark, sf_dir, "documents"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.contamination(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")))


def op10_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages")
    return url_filters.check(url_filters.fetched_pages(pages), url_filters.derived_list(pages), ["page_id"])


def queries() -> dict[str, Query]:
    operators = (
        op1_token_counts,
        op2_bpe_codec,
        op3_simhash,
        op4_substring_dedup,
        op5_secret_scan,
        op6_html_text,
        op7_language_id,
        op8_jaccard_join,
        op9_decontamination,
        op10_url_filters,
    )
    return {f.__name__: f for f in operators}


def oracle_sql() -> dict[str, str]:
    return {"op10_url_filters": url_filters.oracle_sql()}
