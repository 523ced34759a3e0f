"""The curation pipeline end to end, its presets and incremental ingestion.

Steps: rules, distillation of missing responses, dual sampling with length difficulty, removal of overlap with the
benchmark and inside the pool, format checks, routing to verifiers (with regeneration) or the judge, the domain mix
in its ratio, and the curriculum. Records without an id, language or text do not pass the rules.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import grams
from sparkcurate.operators.cluster import encode, encode_md5
from sparkcurate.operators.decontam import COSINE, contaminated_any, max_cosine
from sparkcurate.operators.dedup import drop_contained
from sparkcurate.operators.mix import curriculum, mix
from sparkcurate.operators.quality import ModelClient, StubClient, distill, route, verify_regenerate_stub
from sparkcurate.operators.rules import filter_complete, filter_judged, filter_language, format_reasons
from sparkcurate.operators.select import dual, sample_balanced
from sparkcurate.operators.semantic import combine_rejections
from sparkcurate.plans.strategies import scored_documents
from sparkcurate.sources.tables import table


@dataclass(frozen=True)
class Config:
    """``order`` "late" removes overlap after sampling, "early" before; they select different sets.

    ``share`` of the eligible records is sampled. ``waived`` format reasons do not reject: the stand-in documents
    are prose, which holds neither boxed answers nor programs. ``fitted`` clusters are k-means over question vectors;
    otherwise clusters and vectors are whole-number sums of digests, which SQL can repeat.
    """

    share: float = 0.15
    languages: tuple[str, ...] = ("en",)
    dedup_n: int = 20
    tau: float = 0.8
    decontam_n: int = 15
    cosine: float = COSINE
    waived: tuple[str, ...] = ("no_boxed_answer", "no_program")
    order: str = "late"
    weights: tuple[tuple[str, int], ...] = (("code", 4), ("math", 4), ("science", 3))
    stage_share: float = 0.7
    fitted: bool = True


def minimum_slice(spark: SparkSession, sf_dir: str, budget: int = 60) -> DataFrame:
    docs = filter_complete(filter_language(table(spark, sf_dir, "documents")))
    picked = sample_balanced(docs.select("doc_id", F.col("source").alias("category"), "n_chars"), "category", budget, [F.desc("n_chars"), F.col("doc_id")])
    text = docs.select("doc_id", "text").join(F.broadcast(picked.select("doc_id")), "doc_id", "left_semi")
    return picked.join(contaminated_any(text, table(spark, sf_dir, "benchmark"), "doc_id"), "doc_id", "left_anti").select("doc_id", "category", "n_chars")


def encode_sums(df: DataFrame, key: str, text_col: str, d: int = 64) -> DataFrame:
    """(id, embedding): sums of signed digests of tokens, not normalised."""
    return encode_md5(df, key, text_col, d).select(key, F.col("v").cast("array<double>").alias("embedding"))


def contaminated(docs: DataFrame, benchmark: DataFrame, config: Config) -> DataFrame:
    """Ids that share an n-gram with the benchmark or lie above the cosine to one of its items."""
    vectors = encode if config.fitted else encode_sums
    semantic = max_cosine(vectors(docs, "doc_id", "text"), vectors(benchmark, "item_id", "text"), "doc_id").filter(F.col("cosine") > config.cosine)
    return combine_rejections(contaminated_any(docs, benchmark, "doc_id", n=config.decontam_n), semantic, "doc_id").select("doc_id")


def routed(rows: DataFrame, config: Config) -> tuple[DataFrame, DataFrame]:
    """Ids of (doc_id, text, domain) that pass the format checks, and of those that then pass their route's verifier or judge."""
    reasons = F.array_except(format_reasons(F.col("text"), F.col("domain")), F.array(*[F.lit(w) for w in config.waived]).cast("array<string>"))
    shaped = route(rows.filter(F.size(reasons) == 0))
    verified = verify_regenerate_stub(shaped.filter("route = 'verify'"), "doc_id").filter("passed").select("doc_id")
    return shaped.select("doc_id"), verified.unionByName(filter_judged(shaped.filter("route = 'judge'")).select("doc_id"))


def _overlap_free(docs: DataFrame, benchmark: DataFrame, config: Config) -> DataFrame:
    clean = docs.join(contaminated(docs, benchmark, config), "doc_id", "left_anti")
    return drop_contained(clean, "doc_id", "text", config.dedup_n, config.tau)


def distilled(docs: DataFrame, client: ModelClient) -> DataFrame:
    """Documents whose text is missing get the client's, a batch at a time; the others never meet Python."""
    gaps = docs.filter(F.col("text").isNull()).select("doc_id", F.lit("").alias("question"), F.col("text").alias("response"))
    told = distill(gaps, client, "doc_id").select("doc_id", F.col("response").alias("__told"))
    filled = docs.filter(F.col("text").isNull()).join(told, "doc_id").withColumn("text", F.col("__told")).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)
    return docs.filter(F.col("text").isNotNull()).unionByName(filled)


def run_pipeline(spark: SparkSession, sf_dir: str, config: Config = Config(), client: ModelClient = StubClient()) -> tuple[DataFrame, DataFrame]:
    """(final rows with their stage, rows in and out of each step). Text is fetched only for what is selected."""
    report: list[tuple[str, int]] = []

    def count(name: str, df: DataFrame) -> DataFrame:
        kept = cut(df)
        report.append((name, kept.count()))
        return kept

    docs = table(spark, sf_dir, "documents")
    benchmark = table(spark, sf_dir, "benchmark")
    report.append(("loaded", docs.count()))
    docs = distilled(docs, client)
    clean = filter_complete(filter_language(docs, config.languages))
    clean = count("rules", clean.select("doc_id"))
    pool = docs.join(clean, "doc_id", "left_semi")
    if config.order == "early":
        pool = docs.join(count("overlap", _overlap_free(pool.select("doc_id", "text"), benchmark, config).select("doc_id")), "doc_id", "left_semi")
    scored = scored_documents(pool, fitted=config.fitted)
    budget = round(config.share * scored.count())
    longest = [F.desc("n_chars"), F.col("doc_id")]
    picked = count("sampled", dual(scored, "doc_id", "category", "cluster", budget, longest).select("doc_id"))
    text = docs.join(picked, "doc_id", "left_semi").select("doc_id", "text")
    if config.order == "late":
        text = docs.select("doc_id", "text").join(count("overlap", _overlap_free(text, benchmark, config).select("doc_id")), "doc_id", "left_semi")
    shaped, passed = routed(cut(text.join(scored.select("doc_id", "domain"), "doc_id")), config)
    count("format", shaped)
    rows = scored.join(count("verified", passed), "doc_id", "left_semi")
    mixed = count("mixed", mix(rows, dict(config.weights), None, longest).select("doc_id", "domain", "category", "n_chars"))
    return curriculum(mixed, "doc_id", "n_chars", config.stage_share), spark.createDataFrame(report, "step string, rows long")


def ingest(new: DataFrame, held_grams: DataFrame, benchmark: DataFrame, key: str = "doc_id", n: int = 20) -> tuple[DataFrame, DataFrame]:
    """A new source against what is held: (accepted records, grams to hold from now on); the held text is not read."""
    clean = new.join(contaminated_any(new, benchmark, key), key, "left_anti")
    own = grams(clean, key, "text", n)
    known = own.join(held_grams.select("gram").distinct(), "gram", "left_semi").select(key).distinct()
    accepted = clean.join(known, key, "left_anti")
    fresh = own.join(accepted.select(key), key, "left_semi").select("gram").distinct()
    return accepted, held_grams.select("gram").unionByName(fresh)
