"""The corpus pipeline: each stage works on all that the one before it kept, and its decisions take effect.

Each function takes (spark, docs, sf_dir); run() writes what a stage returns as Parquet in the shared folder and reads
it again as the next one's docs. All stages but the last return the columns of documents.

Cases: null and empty texts, and texts of fewer than ten words, go in the first stage; rows that are alike in doc_id and text are one
document; of rows with one doc_id and different texts each is a document; rows with a null doc_id link with nothing and
stay; further columns of documents, whatever their names, are carried to the last stage but one; empty tables give no rows; without
benchmark items nothing is dropped for them. No text that leaves the second stage is blank.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.llm.decontaminate import without_benchmark
from neardup.llm.lines import WORDS, run_dedup
from neardup.llm.pieces import encode_digests
from neardup.llm.quality import quality_filter
from neardup.llm.shingle_join import one_of_each
from neardup.session import materialize, ship_package

#: Documents that share so many of their words in whole lines, and are about as long, may be versions of one.
VERSION_SHARE = 0.2
#: SQL cannot express the encoding of the last stage; tests hold run() against a brute-force version.
ORACLE_SQL = None


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that a rule rejects."""
    ship_package(spark)
    return quality_filter(docs)


def repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts later copies of repeated runs of one line or more out of the texts.

    Lines that a document shares with a version of it stay, so that the next stage still sees the two as near duplicates; a document that
    is left with fewer words than the quality rules ask for goes.
    """
    return run_dedup(docs, version_share=VERSION_SHARE, least_left=WORDS, length_column="n_chars" if "n_chars" in docs.columns else None)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the lowest doc_id of each group of near duplicates."""
    ship_package(spark)
    return one_of_each(docs)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark item."""
    ship_package(spark)
    return without_benchmark(docs, spark.read.parquet(f"{sf_dir.rstrip('/')}/benchmark.parquet"))


def piece_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encodes what is left: doc_id, n_tokens, ids_sha256 and decoded_sha256."""
    ship_package(spark)
    return encode_digests(docs, public_tokenizers.path("piece_bpe_32k.model"))


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", repeated_lines),
    ("ngram_jaccard_join", near_duplicates),
    ("decontamination", benchmark_passages),
    ("sentencepiece", piece_ids),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = spark.read.parquet(f"{sf_dir.rstrip('/')}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
