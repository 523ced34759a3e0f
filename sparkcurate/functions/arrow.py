"""Arrow-batch functions on executors, with this package shipped to them."""

from __future__ import annotations

import ctypes
import tempfile
import zipfile
from collections.abc import Callable
from functools import lru_cache, wraps
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

PACKAGE = Path(__file__).resolve().parent.parent
_shipped: dict[str, bool] = {}

# The C library's names for the sizes from which memory is mapped alone and given back, and for its arenas.
_MAPPED_FROM, _GIVEN_BACK_FROM, _ARENAS = -3, -1, -8


def ship_package(spark: SparkSession) -> None:
    """Gives executors the package through Spark's own file server, once a Spark application."""
    context = spark.sparkContext
    if _shipped.get(context.applicationId):
        return
    archive = Path(tempfile.mkdtemp(prefix="package")) / f"{PACKAGE.name}.zip"
    with zipfile.ZipFile(archive, "w") as out:
        for source in sorted(PACKAGE.rglob("*.py")):
            out.write(source, source.relative_to(PACKAGE.parent))
    context.addPyFile(str(archive))
    _shipped[context.applicationId] = True


@lru_cache(maxsize=1)
def _give_back() -> Callable[[], None]:
    """Makes this worker return freed memory to the system; calling the result returns what is free now.

    Workers live through many tasks and stages; without this each keeps the most it ever held.
    """
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        c = ctypes.CDLL(None)
        for name, value in ((_MAPPED_FROM, 4 << 20), (_GIVEN_BACK_FROM, 8 << 20), (_ARENAS, 1)):
            c.mallopt(name, value)
        trim = c.malloc_trim
    except (OSError, AttributeError):
        # another C library: nothing to return
        return lambda: None
    return lambda: trim(0)


_kept: dict[tuple, object] = {}


def kept(make: Callable, *args):
    """``make(*args)``, which this worker keeps for later tasks; what it kept before goes first.

    A worker serves all operators of a session in turn, so one model is kept, and only until a task of another module.
    """
    key = (make.__module__, make.__qualname__, *args)
    if key not in _kept:
        _kept.clear()
        _kept[key] = make(*args)
    return _kept[key]


def _begin(module: str) -> Callable[[], None]:
    """What other modules keep goes; the result gives freed memory back."""
    give_back = _give_back()
    others = [key for key in _kept if key[0] != module]
    for key in others:
        del _kept[key]
    if others:
        give_back()
    return give_back


def _batches(run):
    @wraps(run)
    def tidy(batches):
        give_back = _begin(run.__module__)
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidy


def _group(run):
    def tidy(key, table):
        _begin(run.__module__)
        return run(key, table)

    return tidy


def map_arrow(df: DataFrame, run, schema: str | StructType) -> DataFrame:
    ship_package(df.sparkSession)
    return df.mapInArrow(_batches(run), schema)


def group_arrow(df: DataFrame, keys: list[str], run, schema: str | StructType) -> DataFrame:
    ship_package(df.sparkSession)
    return df.groupBy(*keys).applyInArrow(_group(run), schema)
