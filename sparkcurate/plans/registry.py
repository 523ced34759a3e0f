"""All queries of the reference's methods, each with its oracle; filled by the modules below."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Registers a query and, where SQL can express it, its oracle."""

    def add(run: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = run
        if sql is not None:
            ORACLES[name] = sql
        return run

    return add


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Filtered, balanced by source, longest first, free of benchmark 15-grams."""
    from sparkcurate.plans.pipeline import minimum_slice

    return minimum_slice(spark, sf_dir)


def _load() -> None:
    from sparkcurate.plans import queries_core, queries_measures, queries_more, queries_relational, queries_select, queries_stream  # noqa: F401


_load()
