"""Domain mixes, exact quotas and the two-stage curriculum.

Defined cases, for all operators here: rows whose domain has no weight (null too) are left out of a mix and come after
the priority domains in a curriculum; a budget beyond the supply gives all; ties are settled by what the order says
next; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkcurate.operators.select import top_per_group


def apportion(sizes: dict[str, int], weights: dict[str, int], budget: int) -> dict[str, int]:
    """Rows of each domain by highest averages; what a domain lacks goes to the others, ties to the first name."""
    unit = math.lcm(*weights.values())
    given = {d: 0 for d in weights}
    # seats by the integer key (2 r - 1) * unit / weight; a binary search finds the last key within the budget
    count = lambda key: {d: min(sizes.get(d, 0), (key * weights[d] // unit + 1) // 2) for d in weights}
    low, high = 0, 2 * (budget + 1) * unit
    while low < high:
        middle = (low + high + 1) // 2
        if sum(count(middle).values()) <= budget:
            low = middle
        else:
            high = middle - 1
    given = count(low)
    rest = budget - sum(given.values())
    for d in sorted(weights, key=lambda d: ((2 * given[d] + 1) * unit // weights[d], d)):
        if rest > 0 and given[d] < sizes.get(d, 0):
            given[d] += 1
            rest -= 1
    return given


def ratio_budget(sizes: dict[str, int], weights: dict[str, int]) -> int:
    """The most rows that the domains at hand can give in the ratio of their weights."""
    held = {d: w for d, w in weights.items() if sizes.get(d, 0)}
    return min((sizes[d] * sum(held.values()) // w for d, w in held.items()), default=0)


def _take(df: DataFrame, domain: str, given: dict[str, int], order: list[Column]) -> DataFrame:
    plan = [(d, n) for d, n in given.items() if n]
    if not plan:
        return df.limit(0)
    quota = df.sparkSession.createDataFrame(plan, f"{domain} string, __quota int")
    ranked = top_per_group(df.join(F.broadcast(quota), domain), [domain], order, max(n for _, n in plan))
    return ranked.filter(F.col("rn") <= F.col("__quota")).drop("__quota", "rn")


def mix(df: DataFrame, weights: dict[str, int], budget: int | None, order: list[Column], domain: str = "domain") -> DataFrame:
    """Rows in the ratio of the weights, what a domain lacks given by the others; without a budget as many as keep the ratio."""
    sizes = {r[domain]: r["n"] for r in df.groupBy(domain).agg(F.count(F.lit(1)).alias("n")).collect()}
    return _take(df, domain, apportion(sizes, weights, ratio_budget(sizes, weights) if budget is None else budget), order)


def mix_counts(df: DataFrame, counts: dict[str, int], order: list[Column], domain: str = "domain") -> DataFrame:
    return _take(df, domain, counts, order)


def curriculum(df: DataFrame, key: str, length: str, share: float = 0.7, priority: tuple[str, ...] = ("math", "code"), domain: str = "domain") -> DataFrame:
    """Rows with ``stage`` 1 (the simplest share, priority domains first) or 2; stage 2 trains on both.

    The cut is found without a global sort: class and length counts are summed in order, and only
    the rows of the one length at the cut are ranked.
    """
    first = F.when(F.col(domain).isin(*priority), 0).otherwise(1) if priority else F.lit(0)
    marked = df.withColumn("__class", first)
    counts = marked.groupBy("__class", length).agg(F.count(F.lit(1)).alias("__n"))
    below = Window.orderBy("__class", length).rowsBetween(Window.unboundedPreceding, -1)
    total = df.count()
    cut = math.floor(total * share + 1e-9)
    # one row a class and length: sums of the distinct lengths, not of the records
    placed = counts.withColumn("__before", F.coalesce(F.sum("__n").over(below), F.lit(0)))
    split = placed.filter((F.col("__before") < cut) & (F.col("__before") + F.col("__n") > cut)).select("__class", length, "__before")
    inside = placed.withColumn("__whole", F.col("__before") + F.col("__n") <= cut).select("__class", length, "__whole", "__before")
    rank = Window.partitionBy("__class", length).orderBy(key)
    edge = marked.join(F.broadcast(split), ["__class", length]).withColumn("__rn", F.row_number().over(rank)).withColumn("stage", F.when(F.col("__before") + F.col("__rn") <= cut, 1).otherwise(2)).drop("__before", "__rn")
    rest = marked.join(F.broadcast(split.select("__class", length)), ["__class", length], "left_anti").join(inside, ["__class", length]).withColumn("stage", F.when(F.col("__whole"), 1).otherwise(2)).drop("__whole", "__before")
    return edge.unionByName(rest).drop("__class")
