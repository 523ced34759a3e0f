"""Preference pairs and their loss.

Defined cases: null and empty texts overlap nothing; a prompt without a false answer makes no pair, and an id given
twice makes one for each combination; equal or null sides fail the job; the loss over no rows is null; other columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.text import grams
from sparkcurate.operators.select import top_per_group


def overlap_with(df: DataFrame, tuned: DataFrame, key: str, text_col: str = "text", n: int = 20) -> DataFrame:
    """Ids that share an n-gram with the tuning set; both sides are shuffled by gram, neither is broadcast."""
    held = grams(tuned, key, text_col, n).select("gram").distinct()
    return grams(df, key, text_col, n).join(held, "gram", "left_semi").select(key).distinct()


def candidates(df: DataFrame, tuned: DataFrame, contaminated: DataFrame, key: str, text_col: str = "text", n: int = 20) -> DataFrame:
    """Records neither contaminated nor overlapping the tuning set."""
    clean = df.join(contaminated.select(key), key, "left_anti")
    return clean.join(overlap_with(clean, tuned, key, text_col, n), key, "left_anti")


def select_longest(df: DataFrame, groups: list[str], q: int, length: str, key: str) -> DataFrame:
    return top_per_group(df, groups, [F.desc(length), F.col(key)], q).drop("rn")


def build_pairs(strong: DataFrame, false: DataFrame, key: str) -> DataFrame:
    """(id, prompt, chosen, rejected, domain, category); a pair whose sides are equal fails the job."""
    joined = strong.join(false.select(key, F.col("response").alias("rejected")), key)
    check = F.assert_true(F.col("response") != F.col("rejected"), "chosen equals rejected").isNull()
    return joined.filter(check).select(key, F.col("question").alias("prompt"), F.col("response").alias("chosen"), "rejected", "domain", "category")


def softplus(x: Column) -> Column:
    """log(1 + exp(x)) without overflow."""
    return F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))


def preference_loss(df: DataFrame, beta: float = 0.1) -> DataFrame:
    """Loss, reward margin and accuracy over (pol_chosen, ref_chosen, pol_rejected, ref_rejected)."""
    margin = beta * ((F.col("pol_chosen") - F.col("ref_chosen")) - (F.col("pol_rejected") - F.col("ref_rejected")))
    return df.select(margin.alias("m")).agg(F.avg(softplus(-F.col("m"))).alias("loss"), F.avg("m").alias("margin"), F.avg((F.col("m") > 0).cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("n"))
