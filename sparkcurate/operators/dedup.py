"""Overlap removal inside a pool: exact, n-gram and sketch variants, pair and group semantics.

Defined cases, for all operators here: null and empty texts, and texts of fewer than ``n`` tokens, have no n-gram and
overlap nothing (``dedup_exact`` takes null for empty); equal texts overlap wholly; ties in priority go to the smaller
id; ids are expected to be unique (rows that share one are kept or dropped together); an empty table gives no rows;
other columns pass through or are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import gram_hashes, grams, tokens
from sparkcurate.operators.components import connected_components

N = 20


def dedup_exact(df: DataFrame, key: str, text_col: str) -> DataFrame:
    """(id, kept): the smallest id of each text stays."""
    digest = df.select(key, F.md5(F.coalesce(F.col(text_col), F.lit(""))).alias("__d"))
    first = digest.groupBy("__d").agg(F.min(key).alias("__first"))
    return digest.join(first, "__d").select(key, (F.col(key) == F.col("__first")).alias("kept"))


def overlap_pairs(df: DataFrame, key: str, text_col: str, n: int = N, tau: float = 0.8, max_df: int | None = None) -> DataFrame:
    """(a, b, shared, containment): pairs whose shared n-grams are a share of the smaller set of at least tau.

    Grams of more than ``max_df`` records (templates) are left out of both the sets and the join, which
    also bounds the join's groups; without that bound only the rarest grams of each set are joined.
    """
    if max_df is None:
        return dedup_minhash(df, key, text_col, n, tau)
    each = cut(grams(df, key, text_col, n))
    counted = each.groupBy("gram").agg(F.count(F.lit(1)).alias("df"))
    each = each.join(counted.filter(F.col("df") > max_df).select("gram"), "gram", "left_anti")
    # grams of one record make no pair and never reach the join
    shared = counted.filter((F.col("df") > 1) & (F.col("df") <= max_df)).select("gram")
    sizes = each.groupBy(key).agg(F.count(F.lit(1)).alias("size"))
    met = each.join(shared, "gram")
    pairs = met.select(F.col(key).alias("a"), "gram").join(met.select(F.col(key).alias("b"), "gram"), "gram").filter("a < b")
    found = pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    sized = found.join(sizes.select(F.col(key).alias("a"), F.col("size").alias("sa")), "a").join(sizes.select(F.col(key).alias("b"), F.col("size").alias("sb")), "b")
    return sized.withColumn("containment", F.col("shared") / F.least("sa", "sb")).filter(F.col("containment") >= tau).select("a", "b", "shared", "containment")


def drop_contained(df: DataFrame, key: str, text_col: str, n: int = N, tau: float = 0.8, priority: str | None = None) -> DataFrame:
    """Pair semantics over all overlapping records, copies included: a record goes if a partner ranks ahead of it.

    Equal texts are compared once, through the record of theirs that ranks first; the others go, and no pairs are
    made of them, so a group of copies costs its size and not the square.
    """
    rank = F.lit(0) if priority is None else F.col(priority)
    named = df.select(F.col(key).alias("__k"), rank.alias("__p"), F.coalesce(F.col(text_col), F.lit("")).alias("__t")).withColumn("__d", F.md5("__t"))
    best = F.struct((-F.col("__p")).alias("p"), F.col("__k").alias("k"))
    heads = cut(named.groupBy("__d").agg(F.min(best).alias("best"), F.min("__t").alias("__t")).select("__d", F.col("best.k").alias("__k"), (-F.col("best.p")).alias("__p"), "__t"))
    pairs = overlap_pairs(heads, "__k", "__t", n, tau).select("a", "b")
    lost = drop_by_pairs(heads.select("__k", "__p"), "__k", pairs, "__p")
    # what is left: first of its text and not behind another text; short texts overlap nothing and stay
    short = named.filter(F.size(tokens(F.col("__t"))) < n).select("__k")
    return df.join(lost.select(F.col("__k").alias(key)).unionByName(short.select(F.col("__k").alias(key))).distinct(), key, "left_semi")


def shares_any(df: DataFrame, key: str, text_col: str, n: int = N) -> DataFrame:
    """Ids that share an n-gram with a smaller id; no pair is made, and the grams move once for both of their uses."""
    each = grams(df, key, text_col, n).repartition("gram")
    first = each.groupBy("gram").agg(F.min(key).alias("__first"), F.count(F.lit(1)).alias("__n")).filter("__n > 1")
    return each.join(first, "gram").filter(F.col(key) > F.col("__first")).select(key).distinct()


def drop_by_pairs(df: DataFrame, key: str, pairs: DataFrame, priority: str | None = None) -> DataFrame:
    """Pair semantics: a record goes if a partner ranks ahead of it (larger priority, then smaller id)."""
    if priority is None:
        return df.join(pairs.select(F.col("b").alias(key)).distinct(), key, "left_anti")
    rank = df.select(F.col(key).alias("__k"), F.col(priority).alias("__p"))
    both = pairs.join(rank.select(F.col("__k").alias("a"), F.col("__p").alias("pa")), "a").join(rank.select(F.col("__k").alias("b"), F.col("__p").alias("pb")), "b")
    gone = both.select(F.when(F.col("pb") > F.col("pa"), F.col("a")).otherwise(F.col("b")).alias(key)).distinct()
    return df.join(gone, key, "left_anti")


def duplicate_groups(df: DataFrame, key: str, pairs: DataFrame) -> DataFrame:
    """(id, group): group semantics, the smallest id of the connected records."""
    parts = connected_components(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    return df.select(key).join(parts.select(F.col("node").alias(key), "component"), key, "left").select(key, F.coalesce("component", key).alias("grp"))


def dedup_minhash(df: DataFrame, key: str, text_col: str, n: int = N, tau: float = 0.8) -> DataFrame:
    """(a, b, shared, containment): all pairs of at least tau, found by sketches and verified by the gram sets.

    A record's sketch is its rarest grams (equally rare ones by hash), one more than a partner may lack at ``tau``:
    a record at least as large that contains a share of tau has one of them, whatever its size. No pair is lost, and
    only grams of sketches are joined.
    """
    words = df.select(key, tokens(F.col(text_col)).alias("__t"))
    # cut before the filter, which would else make the grams twice
    sets = cut(words.select(key, F.array_distinct(gram_hashes(F.col("__t"), n)).alias("grams"))).filter(F.size("grams") > 0)
    each = sets.select(key, F.size("grams").alias("size"), F.explode("grams").alias("gram"))
    shared = each.groupBy("gram").agg(F.count(F.lit(1)).alias("df")).filter("df > 1")
    met = cut(each.join(shared, "gram"))
    mine = Window.partitionBy(key)
    # the grams of no other record come first in every sketch
    place = F.col("size") - F.count(F.lit(1)).over(mine) + F.row_number().over(mine.orderBy("df", "gram"))
    sketch = met.withColumn("place", place).filter(F.col("place") <= F.col("size") - F.ceil(F.col("size") * tau - 1e-9) + 1)
    small = sketch.select(F.col(key).alias("s"), F.col("size").alias("ss"), "gram")
    large = met.select(F.col(key).alias("t"), F.col("size").alias("st"), "gram")
    pairs = small.join(large, "gram").filter("st >= ss AND s <> t").select(F.least("s", "t").alias("a"), F.greatest("s", "t").alias("b")).distinct()
    both = pairs.join(sets.select(F.col(key).alias("a"), F.col("grams").alias("ga")), "a").join(sets.select(F.col(key).alias("b"), F.col("grams").alias("gb")), "b")
    counted = both.select("a", "b", F.size(F.array_intersect("ga", "gb")).cast("long").alias("shared"), F.least(F.size("ga"), F.size("gb")).alias("least"))
    return counted.withColumn("containment", F.col("shared") / F.col("least")).filter(F.col("containment") >= tau).drop("least")
