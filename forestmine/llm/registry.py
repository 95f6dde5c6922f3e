"""Queries of this folder, by name, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import license_scan, mixing, near_dup, personal_data, quality_rules, sentencepiece_codec, sql, substring_dedup, suffix_tree_lm, token_counts, topk_search
from ._spark import table


def tokenizer_path(name: str) -> str:
    """Where the box keeps a public tokenizer's file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir))


def op2_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir))


def op3_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir), k=4)


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_tree_lm.score_texts(table(spark, sf_dir))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir), tokenizer_path("byte_bpe_50k.json"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.dedup_substrings(table(spark, sf_dir)).drop("kept_text")


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality(table(spark, sf_dir), table(spark, sf_dir, "labels"))


def op8_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(topk_search.scaled_embeddings(table(spark, sf_dir, "embeddings")), F.col("id") % 20 == 0)


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data.find_personal_data(table(spark, sf_dir))


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.round_trip(table(spark, sf_dir), tokenizer_path("piece_bpe_32k.model"))


#: Base columns of the operators whose other columns SQL can't express, each from its operator: query, columns, SQL.
BASE = {
    "base_license_scan": (op1_license_scan, ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels"], sql.LICENSE_BASE),
    "base_lm_scoring": (op4_lm_scoring, ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "round(base_score, 4) AS base_score"], sql.LM_BASE),
    "base_token_counts": (op5_token_counts, ["doc_id", "n_bytes"], sql.TOKEN_BYTES),
    "base_quality_rules": (op7_quality_rules, ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"], sql.QUALITY_BASE),
    "base_personal_data": (op9_personal_data, ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256"], sql.PERSONAL_DATA_BASE),
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_license_scan, op2_source_mixing, op3_minhash_near_dedup, op4_lm_scoring, op5_token_counts, op6_substring_dedup, op7_quality_rules, op8_topk_search, op9_personal_data, op10_sentencepiece]
    base = {name: (lambda spark, sf_dir, f=f, columns=columns: f(spark, sf_dir).selectExpr(*columns)) for name, (f, columns, _) in BASE.items()}
    return {**{f.__name__: f for f in found}, **base}


def oracle_sql() -> dict[str, str]:
    return {"op2_source_mixing": sql.mixing_sql(), "op3_minhash_near_dedup": sql.NEAR_DUP, "op6_substring_dedup": sql.SUBSTRING_DEDUP, "op8_topk_search": sql.TOP_K, **{name: text for name, (*_, text) in BASE.items()}}
