"""Queries of the training-data operators with production parameters, and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkcurate.llm import oracles
from sparkcurate.llm.decontaminate import decontaminate
from sparkcurate.llm.jaccard_join import similar_documents
from sparkcurate.llm.language_id import identify_languages
from sparkcurate.llm.licenses import scan_licenses
from sparkcurate.llm.native import read_table
from sparkcurate.llm.packing import pack_documents
from sparkcurate.llm.parsing_dedup import remove_repeats
from sparkcurate.llm.sharding import assign_shards
from sparkcurate.llm.spotsigs import fingerprint_neighbours
from sparkcurate.llm.token_counts import section_tokens
from sparkcurate.llm.toxicity import score_toxicity


def op4_winnowing_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op5_jump_hash_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign_shards(read_table(spark, sf_dir, "documents"))


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(read_table(spark, sf_dir, "documents"))


def op8_prefix_free_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = remove_repeats(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op9_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_documents(read_table(spark, sf_dir, "documents"))


def op10_karmarkar_karp_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op3_section_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return section_tokens(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op1_boosted_tree_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_toxicity(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op2_cross_parsing_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify_languages(read_table(spark, sf_dir, "documents"))


def op7_spotsigs_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_neighbours(read_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_boosted_tree_toxicity, op4_winnowing_decontamination, op5_jump_hash_shards, op6_license_scan, op8_prefix_free_dedup, op9_ngram_jaccard_join, op10_karmarkar_karp_packing, op3_section_token_counts, op2_cross_parsing_language, op7_spotsigs_fingerprints)
}

ORACLES: dict[str, str] = {
    "op4_winnowing_decontamination": oracles.DECONTAMINATION,
    "op5_jump_hash_shards": oracles.SHARDS,
    "op6_license_scan": oracles.licenses(),
}
