"""The corpus pipeline: quality rules, line dedup, near duplicates, decontamination, tokenising.

Each stage works on all that the one before kept; what it decides takes effect. Between stages the
documents are written as Parquet to the shared folder and read again.

Cases. Each row is judged by its own text, so a null or repeated doc_id takes no other row along: quality
rules and decontamination judge rows; lines are placed by doc_id and text; of near duplicates the least
doc_id stays, rows with a null doc_id all stay, and so do rows that repeat a staying one in doc_id and
text. A null or empty text fails the quality rules. Without trusted labels only the base rules decide,
without test items nothing leaks. Empty tables give an empty result. Further columns of documents are
kept up to the last stage, whatever their names.
"""

from __future__ import annotations

import public_tokenizers
from lexfold.llm.bpe_codec import digests
from lexfold.llm.common import fresh_dir, table
from lexfold.llm.decontamination import without_leaks
from lexfold.llm.line_dedup import without_repeated_lines
from lexfold.llm.ngram_join import one_of_each_group
from lexfold.llm.quality_rules import without_rejected
from pyspark.sql import DataFrame, SparkSession


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the likelihood ratio reject go."""
    return without_rejected(docs, table(spark, sf_dir, "labels").where("quality = 1"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat an earlier one go, and documents of which nothing is left."""
    return without_repeated_lines(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by similar sets of five-word shingles, the one of the least doc_id stays."""
    return one_of_each_group(docs, width=5, percent=80)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return without_leaks(docs, table(spark, sf_dir, "benchmark"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded bytes."""
    return digests(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("quality rules", quality),
    ("line dedup", lines),
    ("n-gram Jaccard join", near_duplicates),
    ("benchmark decontamination", decontaminated),
    ("byte-level BPE", tokens),
]

#: No SQL: hashed likelihood ratios and BPE ids are beyond it; tests hold run() against plain Python.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            path = fresh_dir(spark, f"pipeline-{k}")
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
    return docs
