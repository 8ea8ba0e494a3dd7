"""The corpus pipeline: five stages from raw documents to packed sequences.

Each stage is a function (spark, docs, sf_dir) -> DataFrame; its rows are written
as Parquet and read again as the next stage's docs.  All but the last return the
columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from hushgrad.llm import near_dedup, packing, quality_classifier, quality_rules, store, substring_dedup

WORD_VOCABULARY = "word_bpe_49k.json"

#: Near copies of the pipeline, from 0.8 (op5's contract is 0.85).  32 bands of 4 miss a pair at 0.8
#: with probability (1 - 0.8**4)**32 < 1e-7; the 24 bands of 5 of op5 would miss 7e-5.
NEAR = near_dedup.Params(percent=80, bands=32, rows=4)


def apply_quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules or are depleted go; lines above the limit go from the rest.

    A group of near copies counts as one document, or all of it would lose the lines it shares before
    near-dedup can keep one."""
    store.small_batches(spark)
    return quality_rules.filter_documents(docs, near=NEAR)


def apply_quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below the threshold go.  The model is fitted on labelled rows of the stage's own input."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality_classifier.filter_documents(docs, quality_classifier.train(docs, labels))


def apply_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the smallest id, stays of each group of near-duplicates."""
    return near_dedup.deduplicate(docs, NEAR)


def apply_substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words or more that occur earlier are cut."""
    return substring_dedup.filter_documents(docs)


def apply_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of 4096 tokens."""
    return packing.pack(docs, public_tokenizers.path(WORD_VOCABULARY))


STAGES = [
    ("quality_rules", apply_quality_rules),
    ("quality_classifier", apply_quality_classifier),
    ("minhash_near_dedup", apply_near_dedup),
    ("substring_dedup", apply_substring_dedup),
    ("best_fit_packing", apply_packing),
]

#: No SQL expresses the trained classifier or the packing; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = store.settle(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
