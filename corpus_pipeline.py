"""From documents to packed sequences: quality classifier, near-duplicates, secrets, packing.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept, and is written as Parquet before the
next begins.  All but the last return the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave.llm import cotraining, packing, secret_scan, similar
from spanweave.llm.shared import settle, table


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier accepts."""
    model = cotraining.fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return cotraining.scored(docs, model).where(F.col("quality_score") >= cotraining.GOOD_FROM).select(docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose sets of five-word shingles are alike by 0.8 or more, that with the smallest id."""
    return similar.keep_one(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, with secrets replaced by a mark and n_chars brought up to date."""
    found = secret_scan.scan(docs)
    clean = F.when(F.size("all_spans") > 0, secret_scan.redacted(F.col("text"), F.col("all_spans"))).otherwise(F.col("text"))
    out = found.withColumn("text", clean)
    n_chars = F.when(F.size("all_spans") > 0, F.char_length("text")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", n_chars.cast(docs.schema["n_chars"].dataType)).select(docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences in curve order, with their token ids' checksum."""
    pieces = packing.curve_packed(docs, public_tokenizers.path("word_bpe_49k.json"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


STAGES = [("quality", good_documents), ("near_duplicates", one_of_each_group), ("secrets", without_secrets), ("packing", packed)]

#: Training, components and encoding are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over the whole documents table."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
