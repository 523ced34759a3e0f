"""Difficulty proxies: length, entropy, instruction-following difficulty, pass@k, compression, and any other scorer.

Defined cases, for all operators here: null texts count as empty (length by characters stays null); texts without
tokens have length 0, no entropy and no instruction-following difficulty row, and a compression ratio of the empty
text's compressed size; ties in a score are levelled by id; equal rows are scored alike; an empty table gives no
rows; other columns pass through or are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import ship_package
from sparkcurate.functions.text import n_tokens, tokens
from sparkcurate.operators.select import discrete_quantiles, running_sum


def score_length(df: DataFrame, text_col: str = "text", unit: str = "tokens") -> DataFrame:
    return df.withColumn("difficulty", n_tokens(F.col(text_col)) if unit == "tokens" else F.length(text_col).cast("long"))


def difficulty_level(df: DataFrame, score: str, key: str, levels: int = 4, by: str | None = None) -> DataFrame:
    """Level 1 .. levels by equal shares of the ordered scores (inside a group, if one is named); no task sorts all rows or a whole group."""
    placed = running_sum(df, [*([by] if by else []), score, key], F.lit(1), "__before")
    sizes = placed.groupBy(*([F.col(by).alias("__by")] if by else [])).agg(F.count(F.lit(1)).alias("__n"), F.min("__before").alias("__start"))
    joined = placed.join(sizes, F.col(by).eqNullSafe(F.col("__by"))) if by else placed.crossJoin(F.broadcast(sizes))
    at, least, more = F.col("__before") - F.col("__start"), F.floor(F.col("__n") / levels), F.col("__n") % levels
    # the first levels have one row more if the rows cannot be dealt evenly
    edge = more * (least + 1)
    level = F.when(at < edge, F.floor(at / (least + 1)) + 1).otherwise(more + F.floor((at - edge) / F.greatest(least, F.lit(1))) + 1)
    return joined.withColumn("level", level.cast("int")).drop("__before", "__start", "__n", "__by")


def difficulty_level_by_cuts(df: DataFrame, score: str, levels: int = 4, by: str | None = None, accuracy: int = 10_000) -> DataFrame:
    """Level by exact cuts at equal shares of the scores, equal scores alike; only the bins of a sketch that hold a cut are sorted."""
    cuts = discrete_quantiles(df, [by] if by else [], score, [i / levels for i in range(1, levels)], "__cuts", accuracy)
    joined = df.join(F.broadcast(cuts.withColumnRenamed(by, "__by")), F.col(by).eqNullSafe(F.col("__by")), "left") if by else df.crossJoin(F.broadcast(cuts))
    level = F.when(F.col("__cuts").isNotNull(), 1 + F.size(F.filter("__cuts", lambda c: c < F.col(score))))
    return joined.withColumn("level", level).drop("__cuts", "__by")


def token_entropy(df: DataFrame, key: str, text_col: str) -> DataFrame:
    """(id, complexity): entropy in bits of a text's token distribution; a stand-in for a model's rating of its prompt."""
    each = df.select(key, F.explode(tokens(F.col(text_col))).alias("w")).groupBy(key, "w").agg(F.count(F.lit(1)).alias("c"))
    total = each.groupBy(key).agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.log2("c")).alias("s"))
    return total.select(key, F.round(F.log2("n") - F.col("s") / F.col("n"), 6).alias("complexity"))


def unigram_logprob(df: DataFrame, key: str, text_col: str, corpus: DataFrame, corpus_col: str) -> DataFrame:
    """(id, logprob): mean add-one unigram log-probability of a text's tokens under a corpus."""
    counts = corpus.select(F.explode(tokens(F.col(corpus_col))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("c"))
    whole = counts.agg(F.sum("c").alias("total"), F.count(F.lit(1)).alias("kinds"))
    each = df.select(key, F.explode(tokens(F.col(text_col))).alias("w")).groupBy(key, "w").agg(F.count(F.lit(1)).alias("n"))
    priced = each.join(counts, "w", "left").crossJoin(F.broadcast(whole))
    one = F.log((F.coalesce("c", F.lit(0)) + 1) / (F.col("total") + F.col("kinds") + 1))
    return priced.groupBy(key).agg(F.round(F.sum(F.col("n") * one) / F.sum("n"), 6).alias("logprob"))


def score_ifd(df: DataFrame, key: str, question: str, answer: str) -> DataFrame:
    """(id, ifd): loss of the answer given the question over its loss alone, under an add-one unigram model.

    Given the question, a token's chance is the mean of its corpus chance and its share of the question's tokens.
    """
    counts = df.select(F.explode(tokens(F.col(answer))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("c"))
    whole = counts.agg(F.sum("c").alias("total"), F.count(F.lit(1)).alias("kinds"))
    asked = df.select(key, tokens(F.col(question)).alias("q"), tokens(F.col(answer)).alias("a"))
    each = asked.select(key, F.size("q").alias("nq"), F.explode("a").alias("w")).groupBy(key, "nq", "w").agg(F.count(F.lit(1)).alias("n"))
    own = asked.select(key, F.explode("q").alias("w")).groupBy(key, "w").agg(F.count(F.lit(1)).alias("m"))
    priced = each.join(counts, "w").join(own, [key, "w"], "left").crossJoin(F.broadcast(whole))
    alone = (F.col("c") + 1) / (F.col("total") + F.col("kinds"))
    given = F.when(F.col("nq") > 0, 0.5 * alone + 0.5 * F.coalesce("m", F.lit(0)) / F.col("nq")).otherwise(alone)
    return priced.groupBy(key).agg(F.round(F.sum(F.col("n") * F.log(given)) / F.sum(F.col("n") * F.log(alone)), 6).alias("ifd"))


def pass_at_k(n: Column, c: Column, k: int) -> Column:
    """Chance that one of k of n attempts, c of them right, is right; as a product, so no factorial overflows."""
    miss = F.aggregate(F.sequence(F.lit(1), F.lit(k)), F.lit(1.0), lambda acc, i: acc * (n - c - i + 1) / (n - i + 1))
    return F.when(n < k, F.lit(None)).when(n - c < k, F.lit(1.0)).otherwise(1 - miss)


def score_compression(df: DataFrame, key: str, text_col: str) -> DataFrame:
    """(id, ratio): compressed size over size, a stand-in for entropy-based selection."""
    ship_package(df.sparkSession)

    @F.pandas_udf("double")
    def ratio(texts: pd.Series) -> pd.Series:
        return texts.fillna("").map(lambda t: len(zlib.compress(t.encode())) / max(1, len(t.encode())))

    return df.select(key, ratio(F.col(text_col)).alias("ratio"))


Scorer = Callable[[DataFrame, str, str], DataFrame]
_scorers: dict[str, Scorer] = {}


def register_scorer(name: str, scorer: Scorer) -> None:
    """A scorer takes (records, id column, text column) and returns (id, score); a model's goes through a client."""
    _scorers[name] = scorer


def score_with(df: DataFrame, key: str, text_col: str, names: tuple[str, ...]) -> DataFrame:
    """(id, one column a scorer): records that a scorer leaves out have null there."""
    out = df.select(key)
    for name in names:
        found = _scorers[name](df, key, text_col)
        value = next(c for c in found.columns if c != key)
        out = out.join(found.select(key, F.col(value).alias(name)), key, "left")
    return out


register_scorer("length", lambda df, key, text: df.select(key, n_tokens(F.col(text)).alias("score")))
register_scorer("entropy", token_entropy)
register_scorer("compression", score_compression)
register_scorer("variety", lambda df, key, text: df.select(key, (F.size(F.array_distinct(tokens(F.col(text)))) / F.greatest(F.size(tokens(F.col(text))), F.lit(1))).alias("score")))
