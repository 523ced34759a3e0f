"""Removal of records that overlap a held-out benchmark, lexically or by embedding.

The benchmark's grams, 8 bytes and an item's id each, are broadcast while there are at most ``BROADCAST_GRAMS`` of
them (32 MB); beyond that they are joined by a shuffle. Vectors go in blocks of ``BLOCK_ITEMS``, and at
most ``PRODUCTS`` cosines are held at a time.

Defined cases, for all operators here: null and empty texts, and texts of fewer than ``n`` tokens, have no n-gram and
are never contaminated; an empty benchmark contaminates nothing; zero and null vectors have cosine 0 with every item (-1
if there are none); equal rows are treated alike; rows that share an id are kept or dropped together; an empty table
gives no rows; other columns pass through or are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.functions.text import grams

N = 15
COSINE = 0.9
BROADCAST_GRAMS = 2_000_000
BLOCK_ITEMS = 20_000
PRODUCTS = 4_000_000


def broadcast_side(built: DataFrame, most: int = BROADCAST_GRAMS) -> DataFrame:
    """Broadcast if it has at most so many rows; the rows are small and of fixed width."""
    return F.broadcast(built) if built.limit(most + 1).count() <= most else built


def contaminated_any(df: DataFrame, benchmark: DataFrame, key: str, text_col: str = "text", n: int = N) -> DataFrame:
    """Ids that share at least one n-gram with the benchmark."""
    held = grams(benchmark, "item_id", "text", n).select("gram").distinct()
    return grams(df, key, text_col, n).join(broadcast_side(held), "gram", "left_semi").select(key).distinct()


def contaminated_share(df: DataFrame, benchmark: DataFrame, key: str, text_col: str = "text", n: int = N) -> DataFrame:
    """(id, share): the largest share of an item's n-grams that a record holds."""
    held = grams(benchmark, "item_id", "text", n)
    sized = held.join(held.groupBy("item_id").agg(F.count(F.lit(1)).alias("size")), "item_id")
    met = grams(df, key, text_col, n).join(broadcast_side(sized), "gram")
    per = met.groupBy(key, "item_id").agg((F.count(F.lit(1)) / F.max("size")).alias("share"))
    return per.groupBy(key).agg(F.max("share").alias("share"))


def decontaminate_ngrams(df: DataFrame, benchmark: DataFrame, key: str, text_col: str = "text", n: int = N, rule: str = "any", tau: float = 0.5) -> DataFrame:
    hits = contaminated_any(df, benchmark, key, text_col, n) if rule == "any" else contaminated_share(df, benchmark, key, text_col, n).filter(F.col("share") >= tau).select(key)
    return df.join(hits, key, "left_anti")


def _closest(items: np.ndarray, key: str):
    # products of whole numbers are exact, so divided last, as SQL does: a cosine of the threshold itself stays there
    norms = np.sqrt((items * items).sum(axis=1))
    norms = np.where(norms > 0, norms, 1)
    step = max(1, PRODUCTS // len(items))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = np.array(batch.column("__vec").to_pylist(), np.float64).reshape(batch.num_rows, -1)
            size = np.sqrt((vectors * vectors).sum(axis=1))
            size = np.where(size > 0, size, 1)
            best = np.full(batch.num_rows, -1.0)
            for at in range(0, batch.num_rows, step):
                some = slice(at, at + step)
                best[some] = ((vectors[some] @ items.T) / (size[some, None] * norms)).max(axis=1)
            yield pa.RecordBatch.from_arrays([batch.column(key), pa.array(best)], [key, "cosine"])

    return run


def max_cosine(df: DataFrame, items: DataFrame, key: str, vec_col: str = "embedding", item_col: str = "embedding") -> DataFrame:
    """(id, cosine) to the closest item, by matrix products of Arrow batches with one block of items after another."""
    total = items.count()
    shaped = df.select(key, F.col(vec_col).alias("__vec"))
    kind = df.schema[key].dataType.simpleString()
    out: DataFrame | None = None
    blocks = max(1, -(-total // BLOCK_ITEMS))
    for b in range(blocks):
        some = items if blocks == 1 else items.filter(F.pmod(F.xxhash64(item_col), F.lit(blocks)) == b)
        block = np.array([r[0] for r in some.select(item_col).collect()], np.float64)
        if len(block):
            part = map_arrow(shaped, _closest(block, key), f"{key} {kind}, cosine double")
            out = part if out is None else out.unionByName(part)
    if out is None:
        return df.select(key, F.lit(-1.0).alias("cosine"))
    return out if blocks == 1 else out.groupBy(key).agg(F.max("cosine").alias("cosine"))


def decontaminate_cosine(df: DataFrame, items: DataFrame, key: str, threshold: float = COSINE, vec_col: str = "embedding") -> DataFrame:
    """Records whose closest item is above the threshold go (strictly)."""
    hits = max_cosine(df, items, key, vec_col).filter(F.col("cosine") > threshold).select(key)
    return df.join(hits, key, "left_anti")
