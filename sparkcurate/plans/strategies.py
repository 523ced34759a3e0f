"""The compared selection strategies over one scored table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import seeded
from sparkcurate.operators.cluster import cluster, encode, encode_md5
from sparkcurate.operators.difficulty import score_ifd, token_entropy
from sparkcurate.operators.select import dual, first_rows, sample_balanced
from sparkcurate.sources.tables import documents_as_qa

CLUSTERS = 8
DIMENSIONS = 16
ENCODED = 256


def md5_clusters(docs: DataFrame, key: str = "doc_id", text_col: str = "text", k: int = CLUSTERS, d: int = DIMENSIONS) -> DataFrame:
    """(id, cluster): most similar of the vectors of the k smallest ids with tokens; whole-number vectors, ties to the first."""
    vectors = cut(encode_md5(docs, key, text_col, d))
    square = lambda v: F.aggregate(v, F.lit(0).cast("long"), lambda s, x: s + x * x)
    heads = vectors.filter(square(F.col("v")) > 0).orderBy(key).limit(k).collect()
    if not heads:
        return docs.select(key, F.lit(0).alias("cluster"))
    # k vectors of d numbers, as literals: the pass over the rows is narrow
    scores = []
    for h in heads:
        dot = sum((F.get("v", F.lit(i)) * int(x) for i, x in enumerate(h["v"][1:], 1)), F.get("v", F.lit(0)) * int(h["v"][0]))
        scores.append((dot / F.sqrt(F.lit(float(sum(x * x for x in h["v"]))))).cast("double"))
    best = F.greatest(*scores) if len(scores) > 1 else scores[0]
    out = F.when(scores[0] == best, 0)
    for i, s in enumerate(scores[1:], 1):
        out = out.when(s == best, i)
    return vectors.select(key, out.alias("cluster"))


def fitted_clusters(records: DataFrame, key: str = "doc_id", k: int = CLUSTERS, d: int = ENCODED) -> DataFrame:
    """(id, cluster): k-means over the vectors of the questions of all records."""
    vectors = cut(encode(records, key, "question", d))
    if vectors.isEmpty():
        return vectors.select(key, F.lit(0).alias("cluster"))
    return cluster(vectors, key, k)[0].select(key, "cluster")


def scored_documents(docs: DataFrame, seed: int = 42, fitted: bool = False) -> DataFrame:
    """One row a record with every score a strategy needs; without text, checkpointed, read by all strategies.

    Clusters are ``fitted``, or those of ``md5_clusters``, which SQL can repeat.
    """
    records = documents_as_qa(docs).withColumnRenamed("qid", "doc_id")
    entropy = token_entropy(records, "doc_id", "question")
    ifd = score_ifd(records, "doc_id", "question", "response")
    base = records.select("doc_id", "domain", "category", "n_chars", "n_tokens")
    joined = base.join(entropy, "doc_id", "left").join(ifd, "doc_id", "left").join(fitted_clusters(records) if fitted else md5_clusters(docs), "doc_id")
    return cut(joined.withColumn("complexity", F.coalesce("complexity", F.lit(0.0))).withColumn("ifd", F.coalesce("ifd", F.lit(0.0))).withColumn("rnd", seeded("doc_id", seed)))


def _orders() -> dict[str, list[Column]]:
    return {
        "random": [F.col("rnd"), F.col("doc_id")],
        "length": [F.desc("n_chars"), F.col("doc_id")],
        "short": [F.col("n_chars"), F.col("doc_id")],
        "complexity": [F.desc("complexity"), F.col("doc_id")],
        "ifd": [F.desc("ifd"), F.col("doc_id")],
    }


def select(scored: DataFrame, strategy: str, budget: int, ascending: bool = False) -> DataFrame:
    """Ids of one strategy."""
    order = _orders()
    longest = order["short"] if ascending else order["length"]
    plans = {
        "random": lambda: first_rows(scored, order["random"], budget),
        "dual": lambda: dual(scored, "doc_id", "category", "cluster", budget, order["random"]),
        "length": lambda: first_rows(scored, longest, budget),
        "complexity+dual": lambda: dual(scored, "doc_id", "category", "cluster", budget, order["complexity"]),
        "ifd+dual": lambda: dual(scored, "doc_id", "category", "cluster", budget, order["ifd"]),
        "length+embedding": lambda: sample_balanced(scored, "cluster", budget, longest),
        "length+category": lambda: sample_balanced(scored, "category", budget, longest),
        "length+dual": lambda: dual(scored, "doc_id", "category", "cluster", budget, longest),
    }
    return plans[strategy]().select("doc_id")


STRATEGIES = ("random", "dual", "length", "complexity+dual", "ifd+dual", "length+embedding", "length+category", "length+dual")


def run_ablation(scored: DataFrame, strategies: tuple[str, ...], budget: int) -> DataFrame:
    """(strategy, doc_id) of every strategy at one budget; each one's ids are cut, so no plan holds all strategies."""
    out: DataFrame | None = None
    for name in strategies:
        rows = cut(select(scored, name, budget)).select(F.lit(name).alias("strategy"), "doc_id")
        out = rows if out is None else out.unionByName(rows)
    return out


def summary(selected: DataFrame, scored: DataFrame) -> DataFrame:
    """What a strategy picked: size, lengths, labels covered."""
    return selected.join(scored, "doc_id").groupBy("strategy").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg("n_chars"), 6).alias("mean_chars"), F.countDistinct("category").alias("categories"),
        F.countDistinct("cluster").alias("clusters"), F.round(F.avg("complexity"), 6).alias("mean_complexity"), F.round(F.avg("ifd"), 6).alias("mean_ifd"),
    )
