"""Sources: table readers, per-source adapters to one record schema, formats and sinks.

Defined cases: null texts and html stay null (a null text has no question and 0 tokens); turns without an answer have a
null response; columns that a source lacks are null; empty tables give no rows; other columns are dropped by adapters.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparkcurate.functions.text import domain_of_source, leading_sentence, n_tokens

QA_COLUMNS = ("qid", "question", "response", "source", "lang")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def to_qa_pairs(conversations: DataFrame) -> DataFrame:
    """Each user turn with the next turn if that is an assistant's (response null if not)."""
    by_turn = Window.partitionBy("conv_id").orderBy("turn")
    following = conversations.withColumn("__role", F.lead("role").over(by_turn)).withColumn("__text", F.lead("text").over(by_turn))
    return following.filter(F.col("role") == "user").select(
        F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("qid"), "conv_id", "turn", F.col("text").alias("question"),
        F.when(F.col("__role") == "assistant", F.col("__text")).alias("response"),
    )


def documents_as_qa(docs: DataFrame) -> DataFrame:
    """Documents as records: the leading sentence asks, the whole text answers."""
    return docs.select(
        F.col("doc_id").alias("qid"), leading_sentence(F.col("text")).alias("question"), F.col("text").alias("response"), "source", "lang",
        domain_of_source(F.col("source")).alias("domain"), F.col("source").alias("category"), "n_chars", n_tokens(F.col("text")).alias("n_tokens"),
    )


def html_to_text(html: Column) -> Column:
    """Visible text of a page: scripts, styles and tags go, common entities are read, white space is folded."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    bare = F.regexp_replace(bare, r"(?s)<[^>]*>", " ")
    for name, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        bare = F.replace(bare, F.lit(name), F.lit(sign))
    return F.trim(F.regexp_replace(bare, r"[ \t\r\n]+", " "))


_registry: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def register_source(name: str, adapter: Callable[[SparkSession, str], DataFrame]) -> None:
    """An adapter returns the columns of QA_COLUMNS (others are dropped, missing ones are null)."""
    _registry[name] = adapter


def load_sources(spark: SparkSession, location: str, names: Iterable[str] | None = None) -> DataFrame:
    """All named sources in one schema, with the source's name in ``origin``."""
    out: DataFrame | None = None
    for name in names if names is not None else sorted(_registry):
        rows = _registry[name](spark, location)
        shaped = rows.select(*[rows[c].cast("string").alias(c) if c in rows.columns else F.lit(None).cast("string").alias(c) for c in QA_COLUMNS], F.lit(name).alias("origin"))
        out = shaped if out is None else out.unionByName(shaped)
    if out is None:
        raise ValueError("no source is registered")
    return out


register_source("documents", lambda spark, d: documents_as_qa(table(spark, d, "documents")))
register_source("conversations", lambda spark, d: to_qa_pairs(table(spark, d, "conversations")).withColumn("source", F.lit("chat")))
register_source("pages", lambda spark, d: table(spark, d, "pages").select(F.col("page_id").alias("qid"), F.parse_url("url", F.lit("HOST")).alias("source"), html_to_text(F.col("html")).alias("response")))

FORMATS = ("parquet", "json", "csv", "orc", "text")


def read_files(spark: SparkSession, path: str, form: str, schema: str | None = None, glob: str | None = None, **options: str) -> DataFrame:
    """Files of a known format; explicit schema, no inference over the data."""
    if form not in FORMATS:
        raise ValueError(f"unknown format {form}")
    reader = spark.read.options(**options)
    reader = reader.schema(schema) if schema and form != "text" else reader
    reader = reader.option("pathGlobFilter", glob) if glob else reader
    return reader.format(form).load(path)


def write_bucketed(df: DataFrame, path: str, key: str, buckets: int) -> DataFrame:
    """Rows in sorted buckets of a key, so that joins by the key need no shuffle; read back from the path."""
    name = f"bucketed_{uuid.uuid4().hex}"
    df.write.format("parquet").bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
    return df.sparkSession.table(name)


def write_files(df: DataFrame, path: str, form: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "error") -> None:
    writer = df.write.mode(mode).format(form)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
