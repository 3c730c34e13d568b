"""The registered queries of the operators, and SQL for those that SQL expresses."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, cotraining, fingerprints, html_main, lm_score, packing, projected_search, secret_scan, simhash, token_orc
from .shared import table, workspace


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    out = byte_bpe.bpe_round_trip(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    decimal = F.concat_ws(",", F.col("token_ids").cast("array<string>"))
    return out.select("doc_id", F.size("token_ids").cast("long").alias("n_tokens"), F.sha2(decimal, 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op2_curve_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.curve_packed(table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"))
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op3_one_permutation_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = fingerprints.edited_fingerprints(table(spark, sf_dir, "documents", "doc_id", "text"))
    own, edited = fingerprints.as_text(F.col("fingerprint")), fingerprints.as_text(F.col("edited_fingerprint"))
    return out.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), own.alias("fingerprint"), edited.alias("edited_fingerprint"), "near_edited", "near_next")


def op4_cotraining_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source", "n_chars")
    model = cotraining.fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))
    return cotraining.scored(docs, model).select("doc_id", F.round("quality_score", 6).alias("quality_score"), (F.col("quality_score") >= cotraining.GOOD_FROM).alias("kept"))


def op5_entropy_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secret_scan.scan(table(spark, sf_dir, "documents", "doc_id", "text"))
    of_kind = lambda k: F.size(F.filter("base_spans", lambda s: s["kind"] == k)).cast("long")
    counts = [of_kind(k).alias(f"n_{name}") for k, (name, _) in enumerate(secret_scan.BASE)]
    return found.select("doc_id", *counts, F.sha2(secret_scan.span_text(F.col("base_spans")), 256).alias("base_sha256"), secret_scan.span_text(F.col("all_spans")).alias("spans"))


def op6_token_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = workspace(spark)
    token_orc.write_token_orc(table(spark, sf_dir, "documents", "doc_id", "text"), path, public_tokenizers.path("word_bpe_49k.json"))
    return token_orc.id_checksums(token_orc.read_token_orc(spark, path)).select("doc_id", "start", "n_tokens", "ids_crc32")


def op7_simhash_vantage(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", simhash.fingerprint_text(F.col("fp")).alias("fingerprint"), "component_id")


def op8_cross_entropy_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "quality")
    return lm_score.score(docs, labels, public_tokenizers.path("word_bpe_49k.json"))


def op9_projected_kd_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return projected_search.nearest(rows, F.col("vec_id") % 20 == 0, k=20)


def op10_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages", "page_id", "url", "html")
    return html_main.extracted(pages, html_main.fit(pages)).select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_byte_bpe, op2_curve_packing, op3_one_permutation_minhash, op4_cotraining_quality, op5_entropy_secrets, op6_token_orc, op7_simhash_vantage, op8_cross_entropy_difference, op9_projected_kd_tree, op10_main_text)}


def oracle_sql() -> dict[str, str]:
    return {}
