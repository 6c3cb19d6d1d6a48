"""A training corpus from raw documents: five stages, each written and read again as Parquet.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept, and returns a
DataFrame; all but the last return the columns of `documents`.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shoal.core.storage import Scratch, made, remove_made
from shoal.llm import decontaminate, jaccard_join, pieces, quality_rules, substring_dedup


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the quality policy."""
    return quality_rules.keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies (80 % of five-word shingles): the one with the smallest id. Null ids are in no class and stay."""
    gone = jaccard_join.other_copies(docs, width=5, percent=80).select(F.col("doc_id").alias("__gone"), F.col("mark").alias("__mark"))
    return docs.join(gone, (F.col("doc_id") == F.col("__gone")) & (jaccard_join.text_mark("text") == F.col("__mark")), "left_anti")


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the words of passages that a document with a smaller id holds too."""
    return _counted(substring_dedup.remove_repeats(docs))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the words of benchmark passages."""
    return _counted(decontaminate.remove_contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")))


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of the final texts, checked by their digests."""
    return pieces.encoding_digests(docs, public_tokenizers.path("piece_bpe_32k.model"))


def _counted(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality),
    ("ngram_jaccard_join", near_duplicates),
    ("substring_dedup", substrings),
    ("benchmark_decontamination", decontamination),
    ("piece_encoding", encoding),
]

#: Sub-word encoding cannot be expressed in SQL; tests hold the pipeline against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table. What a stage needed is removed when its rows are written."""
    scratch = Scratch(spark, "pipeline")
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for _, stage in STAGES:
        mark = made()
        docs = scratch.write(stage(spark, docs, sf_dir))
        remove_made(spark, mark)
        scratch.drop(before)
        before = docs
    return docs
