"""A corpus pipeline over ``documents``; each stage reads what the one before it wrote.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the
columns of documents.  Rows with a null in any column pass a stage unless its operator's own rule
for them says otherwise.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronocluster.llm import bpe, decontaminate, jaccard_join, language_id, secrets
from chronocluster.llm.common import load, materialise
from chronocluster.llm.registry import tokenizer

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _whole(docs: DataFrame) -> DataFrame:
    return docs.select(*COLUMNS)


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without a language: null texts and texts without a letter."""
    rows = _whole(docs)
    labelled = language_id.identify(rows, COLUMNS, "text", language_id.train(rows))
    return labelled.filter(F.col("lang_pred") != language_id.UNKNOWN).select(*COLUMNS)


def join_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each component of similar ones, the one whose id is smallest.

    Documents without words have no partner and stay, and so do components without any id.  Rows
    that repeat an id within a component are reduced to one.
    """
    rows = _whole(docs)
    found = jaccard_join.similarity_components(spark, rows.select("doc_id", "text"))
    extra = found.filter(~F.col("doc_id").eqNullSafe(F.col("component_id")) & F.col("component_id").isNotNull()).select(F.col("doc_id").alias("gone")).distinct()
    kept = rows.join(materialise(extra, "duplicates"), F.col("doc_id").eqNullSafe(F.col("gone")), "left_anti")
    twice = materialise(found.groupBy("doc_id").agg(F.count("*").alias("n"), F.max("n_shingles").alias("size")).filter("n > 1 and size > 0 and doc_id is not null").select("doc_id"), "repeated")
    single = kept.join(twice, "doc_id", "left_anti").select(*COLUMNS)
    return single.unionByName(kept.join(twice, "doc_id", "left_semi").select(*COLUMNS).dropDuplicates(["doc_id"]))


def decontaminate_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a window of a benchmark item."""
    rows = _whole(docs)
    marked = decontaminate.contamination(rows, load(spark, sf_dir, "benchmark"), carried=COLUMNS)
    return marked.filter(F.size("spans") == 0).select(*COLUMNS)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mask secrets in the texts; n_chars follows where a text has changed."""
    scanned = secrets.scan(_whole(docs), ["doc_id", "lang", "source", "n_chars"], "text", tokenizer("byte_bpe_50k.json"))
    return scanned.select("doc_id", F.col("clean").alias("text"), "lang", "source", F.when(F.size("findings") > 0, F.length("clean").cast("bigint")).otherwise(F.col("n_chars")).alias("n_chars"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with their ids as digests of the encoding and of its decoding."""
    return bpe.encode_decode(_whole(docs), COLUMNS, "text", tokenizer("byte_bpe_50k.json"))


STAGES = [
    ("language_id", identify_language),
    ("jaccard_join", join_near_duplicates),
    ("decontamination", decontaminate_benchmark),
    ("secret_scan", mask_secrets),
    ("bpe_codec", encode),
]
#: The stages learn, hash and tokenise; SQL cannot state them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; between two of them the rows are written to the shared folder."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
