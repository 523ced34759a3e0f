"""Balanced draws, merges and budgets.

A round-robin draw over groups equals water-filling: every group gives min(size, q) rows, and the first
groups in order give one more until the budget is met. Only group sizes reach the driver; rows are ranked
in salted parts of their group first, so a hot group is never sorted by one task alone.

Defined cases, for all operators here: rows without a label (null) are a group of their own, the first in order;
a budget of 0 or less gives no rows and one beyond the supply gives all; ties in the order are settled by what the
order says next, and equal rows each count; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from sparkcurate.functions.lineage import cut

SALTS = 64


def top_per_group(df: DataFrame, groups: list[str], order: list[Column], limit: int | Column, rank: str = "rn", salts: int = SALTS) -> DataFrame:
    """The first rows of each group with their rank; two-phase, so the second phase sees at most salts x limit rows a group."""
    salt = F.pmod(F.xxhash64(*df.columns), F.lit(salts))
    part = Window.partitionBy(*groups, "__salt").orderBy(*order)
    whole = Window.partitionBy(*groups).orderBy(*order)
    some = df.withColumn("__salt", salt).withColumn("__first", F.row_number().over(part)).filter(F.col("__first") <= limit)
    return some.drop("__salt", "__first").withColumn(rank, F.row_number().over(whole)).filter(F.col(rank) <= limit)


def running_sum(df: DataFrame, order: list[str], value: Column, name: str) -> DataFrame:
    """Adds the sum of value over all rows before each in a total order; sorted in ranges, and only a total a range reaches the driver."""
    ranged = cut(df.withColumn("__value", value).repartitionByRange(*order).withColumn("__part", F.spark_partition_id()))
    totals, before = {}, 0
    for r in ranged.groupBy("__part").agg(F.sum("__value").alias("n")).orderBy("__part").collect():
        totals[r["__part"]] = before
        before += r["n"] or 0
    earlier = Window.partitionBy("__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    offset = df.sparkSession.createDataFrame(list(totals.items()), "__part int, __offset long")
    inside = ranged.withColumn("__inside", F.coalesce(F.sum("__value").over(earlier), F.lit(0)))
    return inside.join(F.broadcast(offset), "__part").withColumn(name, F.col("__offset") + F.col("__inside")).drop("__part", "__value", "__offset", "__inside")


def discrete_quantiles(df: DataFrame, groups: list[str], value: str, steps: list[float], name: str, accuracy: int = 10_000, bins: int = 64) -> DataFrame:
    """(groups, array of quantiles): exact values of the ranks that the steps name; null values take no part, null groups do.

    A quantile sketch cuts each group into bins. The bins are counted, and of those that hold a wanted rank the distinct
    values, so the result is exact however near the sketch comes; no task sorts a group.
    """
    held = df.filter(F.col(value).isNotNull()).select(*[F.col(g).alias(f"__g{i}") for i, g in enumerate(groups)], F.col(value).alias("__v"))
    keys = [f"__g{i}" for i in range(len(groups))]

    def beside(left: DataFrame, right: DataFrame, by: list[str], how: str = "inner") -> DataFrame:
        other = right.select(*[F.col(k).alias(f"{k}_") for k in by], *[c for c in right.columns if c not in by])
        joined = left.join(F.broadcast(other), reduce(and_, [F.col(k).eqNullSafe(F.col(f"{k}_")) for k in by], F.lit(True)), how)
        return joined.drop(*[f"{k}_" for k in by])

    sketch = cut(held.groupBy(*keys).agg(F.percentile_approx("__v", [i / bins for i in range(1, bins)], accuracy).alias("__edges"), F.count(F.lit(1)).alias("__n")))
    binned = beside(held, sketch.select(*keys, "__edges"), keys).withColumn("__bin", F.size(F.filter("__edges", lambda e: e < F.col("__v")))).drop("__edges")
    earlier = Window.partitionBy(*keys).orderBy("__bin").rowsBetween(Window.unboundedPreceding, -1)
    counted = binned.groupBy(*keys, "__bin").agg(F.count(F.lit(1)).alias("__c")).withColumn("__below", F.coalesce(F.sum("__c").over(earlier), F.lit(0)))
    ranks = F.array(*[F.struct(F.lit(i).alias("i"), F.greatest(F.col("__n") - F.floor(F.col("__n") - F.col("__n") * p), F.lit(1)).alias("k")) for i, p in enumerate(steps)])
    targets = beside(counted, sketch.select(*keys, "__n"), keys).withColumn("__t", F.explode(ranks)).filter("__below < __t.k AND __t.k <= __below + __c")
    wanted = cut(targets.select(*keys, "__bin", F.col("__t.i").alias("__i"), (F.col("__t.k") - F.col("__below")).alias("__k")))
    inside = beside(binned, wanted.select(*keys, "__bin").distinct(), [*keys, "__bin"], "left_semi").groupBy(*keys, "__bin", "__v").agg(F.count(F.lit(1)).alias("__c"))
    placed = running_sum(inside, [*keys, "__bin", "__v"], F.col("__c"), "__before")
    starts = placed.groupBy(*keys, "__bin").agg(F.min("__before").alias("__start"))
    ranked = beside(placed, beside(wanted, starts, [*keys, "__bin"]), [*keys, "__bin"]).withColumn("__at", F.col("__before") - F.col("__start"))
    found = ranked.filter("__at < __k AND __k <= __at + __c").groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("__i", "__v"))).alias("__f"))
    return found.select(*[F.col(k).alias(g) for k, g in zip(keys, groups)], F.when(F.size("__f") > 0, F.col("__f.__v")).alias(name))


def quotas(sizes: dict[str, int], budget: int) -> dict[str, int]:
    """Rows that each group gives in a round-robin draw of the budget; groups in their order."""
    names = sorted(sizes, key=lambda n: (n is not None, n))
    budget = max(0, min(budget, sum(sizes.values())))
    low, high = 0, max(sizes.values(), default=0)
    while low < high:
        middle = (low + high + 1) // 2
        if sum(min(sizes[n], middle) for n in names) <= budget:
            low = middle
        else:
            high = middle - 1
    given = {n: min(sizes[n], low) for n in names}
    rest = budget - sum(given.values())
    for n in names:
        if rest and sizes[n] > low:
            given[n] += 1
            rest -= 1
    return given


def _given(df: DataFrame, groups: list[str], plan: list[tuple], order: list[Column]) -> DataFrame:
    """The first rows of each group as far as the plan (labels, quota) says."""
    most = max((p[-1] for p in plan), default=0)
    if not most:
        return df.limit(0)
    fields = [StructField(f"__g{i}", df.schema[g].dataType) for i, g in enumerate(groups)]
    quota = df.sparkSession.createDataFrame(plan, StructType([*fields, StructField("__quota", IntegerType())]))
    ranked = top_per_group(df, groups, order, most)
    same = [F.col(g).eqNullSafe(F.col(f"__g{i}")) for i, g in enumerate(groups)]
    joined = ranked.join(F.broadcast(quota), reduce(and_, same))
    return joined.filter(F.col("rn") <= F.col("__quota")).drop("rn", "__quota", *(f.name for f in fields))


def sample_balanced(df: DataFrame, group: str, budget: int, order: list[Column]) -> DataFrame:
    """Equal rows of every group, the first by order; what a small group lacks the others give."""
    sizes = {r[group]: r["n"] for r in df.groupBy(group).agg(F.count(F.lit(1)).alias("n")).collect()}
    return _given(df, [group], list(quotas(sizes, budget).items()), order)


def sample_nested(df: DataFrame, outer: str, inner: str, budget: int, order: list[Column]) -> DataFrame:
    """Balance over the outer label first, then over the inner label in it."""
    sizes: dict[str, dict[str, int]] = {}
    for r in df.groupBy(outer, inner).agg(F.count(F.lit(1)).alias("n")).collect():
        sizes.setdefault(r[outer], {})[r[inner]] = r["n"]
    top = quotas({k: sum(v.values()) for k, v in sizes.items()}, budget)
    plan = [(k, i, q) for k, v in sizes.items() for i, q in quotas(v, top[k]).items()]
    return _given(df, [outer, inner], plan, order)


def first_rows(df: DataFrame, order: list[Column], budget: int) -> DataFrame:
    """The first rows of a total order; a bounded top-k, no global sort."""
    return df.orderBy(*order).limit(budget)


def merge_selections(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Union by id with where each row came from."""
    both = a.select(key, F.lit(True).alias("from_domain"), F.lit(False).alias("from_semantic")).unionByName(b.select(key, F.lit(False).alias("from_domain"), F.lit(True).alias("from_semantic")))
    return both.groupBy(key).agg(F.bool_or("from_domain").alias("from_domain"), F.bool_or("from_semantic").alias("from_semantic"))


def dual(df: DataFrame, key: str, category: str, cluster: str, budget: int, order: list[Column], split: float = 0.5, top_up: bool = True) -> DataFrame:
    """Ids of both draws merged; with ``top_up``, filled to the budget from the domain draw's order. The merged draw is cut: it is counted and read again."""
    first = int(budget * split)
    merged = cut(merge_selections(sample_balanced(df, category, first, order), sample_balanced(df, cluster, budget - first, order), key))
    if not top_up:
        return merged
    missing = min(budget, df.count()) - merged.count()
    if missing <= 0:
        return merged
    rest = df.join(merged.select(key), key, "left_anti")
    more = sample_balanced(rest, category, missing, order).select(key, F.lit(False).alias("from_domain"), F.lit(False).alias("from_semantic"))
    return merged.unionByName(more)
