"""The registered queries of the operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from hushgrad.llm import (
    bpe,
    fingerprints,
    near_dedup,
    oracle,
    packing,
    quality_classifier,
    quality_rules,
    sharding,
    store,
    substring_dedup,
    token_counts,
    token_store,
)

WORD_VOCABULARY = "word_bpe_49k.json"
BYTE_VOCABULARY = "byte_bpe_50k.json"


def _table(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    store.small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprint_with_edit(_table(spark, sf_dir))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    verdicts, _ = quality_rules.evaluate(_table(spark, sf_dir))
    return verdicts.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_line_words_removed"
    )


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.strip_repeats(_table(spark, sf_dir), digest=True)


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir), public_tokenizers.path(WORD_VOCABULARY))


def op5_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.components(_table(spark, sf_dir)).select("doc_id", "n_shingles", "component_id", "kept", "class_id")


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(_table(spark, sf_dir), 40)


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(_table(spark, sf_dir), public_tokenizers.path(BYTE_VOCABULARY))


def op8_token_id_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = store.fresh_path(spark, "token-ids")
    token_store.write(_table(spark, sf_dir), folder, public_tokenizers.path(WORD_VOCABULARY))
    return token_store.read(spark, folder, digest=True).select("doc_id", "start", "n_tokens", "ids_crc32")


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir)
    return quality_classifier.score(docs, quality_classifier.train(docs, _table(spark, sf_dir, "labels")))


def op10_bpe_encode_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(_table(spark, sf_dir), public_tokenizers.path(WORD_VOCABULARY), digest=True)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_document_fingerprints,
        op2_quality_rules,
        op3_substring_dedup,
        op4_best_fit_packing,
        op5_minhash_near_dedup,
        op6_sharding,
        op7_token_counts,
        op8_token_id_output,
        op9_quality_classifier,
        op10_bpe_encode_decode,
    )
}

ORACLE_SQL: dict[str, str] = dict(oracle.SQL)
