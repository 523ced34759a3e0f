"""Corpus pipeline: each stage is written as Parquet and read again as the next one's documents."""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkcurate.functions.lineage import ensure_checkpoint_dir, remove_folder
from sparkcurate.llm.decontaminate import decontaminate
from sparkcurate.llm.jaccard_join import keep_one_of_each
from sparkcurate.llm.language_id import keep_identified
from sparkcurate.llm.native import read_table
from sparkcurate.llm.packing import pack_documents
from sparkcurate.llm.parsing_dedup import strip_repeats


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter go; ``lang`` becomes the identified language."""
    return keep_identified(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays."""
    return keep_one_of_each(docs)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes that repeat a smaller document go; a character that lost a byte goes with it."""
    return strip_repeats(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Contaminated documents go."""
    told = decontaminate(docs, read_table(spark, sf_dir, "benchmark")).filter("contaminated").select(F.col("doc_id").alias("__id"), "__text").distinct()
    text = F.xxhash64(F.coalesce(F.col("text"), F.lit("")))
    return docs.join(told, docs["doc_id"].eqNullSafe(told["__id"]) & (text == told["__text"]), "left_anti")


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language ID", language),
    ("n-gram Jaccard join", near_duplicates),
    ("suffix-array dedup", repeats),
    ("benchmark decontamination", decontamination),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what is written between them lies in the shared checkpoint folder."""
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = read_table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        out.write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:
            # the stage before the last one written is not read again
            remove_folder(spark, f"{folder}/{k - 1}")
    return docs


# cross-parsing, tokenization and differencing are not expressible in SQL; see tests/llm
ORACLE_SQL = None
