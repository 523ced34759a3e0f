"""Joins that Spark lacks as operators: as-of, range and inequality joins as unions, bins and running counts.

Defined cases: rows with a null key or time match nothing (left rows of an as-of join stay, with a null value); of
right rows at the same time the last in the window's order counts, and rows at the left row's own time count as before
it; repeated rows match each; empty tables match nothing; other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkcurate.operators.select import running_sum


def as_of(left: DataFrame, right: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """Each left row with the last right value at or before its time: one union and one window, no join."""
    columns = left.columns
    a = left.withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).withColumn("__side", F.lit(1))
    b = right.select(by, time, F.col(value).alias("__v")).withColumn("__side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    before = Window.partitionBy(by).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(f"last_{value}", F.last("__v", ignorenulls=True).over(before)).filter("__side = 1").select(*columns, f"last_{value}")


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Points with the ranges [low, high) that hold them: an equi-join on bins, each range in the bins it meets."""
    binned = points.withColumn("__bin", F.floor(F.col(point) / width))
    spread = ranges.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor((F.col(high) - 1) / width))))
    return binned.join(spread, "__bin").filter((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("__bin")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Equi-join whose hot left keys are spread: left rows take a salt, right rows are repeated for each.

    Spark plans by the right side's size before it is repeated; the hint keeps the repeated rows out of a broadcast.
    """
    salt: Column = F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int")
    wide = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.withColumn("__salt", salt).join(wide.hint("merge"), [key, "__salt"]).drop("__salt")


def count_before(left: DataFrame, right: DataFrame, value: str, name: str) -> DataFrame:
    """Each left row with the number of right rows whose value is smaller: a running count over both, no pairs."""
    a = left.withColumn("__side", F.lit(0))
    both = a.unionByName(right.select(value, F.lit(1).alias("__side")), allowMissingColumns=True)
    return running_sum(both.filter(F.col(value).isNotNull()), [value, "__side"], F.col("__side").cast("long"), name).filter("__side = 0").drop("__side")
