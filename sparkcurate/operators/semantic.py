"""Semantic overlap of long records: matched chunks, combined rules and the strict pool.

Defined cases: null and empty texts, texts of fewer words than an n-gram, and zero vectors match nothing and stay;
equal texts and vectors are linked to their smallest id; ids are expected to be unique; empty tables give no rows;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import gram_hashes, tokens
from sparkcurate.operators.cluster import encode
from sparkcurate.operators.decontam import BLOCK_ITEMS, COSINE, broadcast_side
from sparkcurate.operators.dedup import overlap_pairs

# numbers of a vector that are multiplied before the rest, and rows in one product
HEAD = 64
PRODUCT_ROWS = 512


def _best_windows(threshold: float):
    """For pairs of gram lists: the largest cosine of a window of the first, as long as the second, with the second."""

    def best(record: np.ndarray, item: np.ndarray) -> float:
        width = min(len(record), len(item))
        names, counts = np.unique(item, return_counts=True)
        at = np.minimum(np.searchsorted(names, record), len(names) - 1)
        value = np.where(names[at] == record, counts[at], 0)
        dots = np.concatenate([[0], np.cumsum(value)])
        dots = dots[width:] - dots[:-width]
        size = np.sqrt(float((counts**2).sum()))
        found = -1.0
        # a window's norm is the root of its length at least
        for s in np.flatnonzero(dots > threshold * size * np.sqrt(width)).tolist():
            own = np.unique(record[s : s + width], return_counts=True)[1]
            found = max(found, float(dots[s] / (size * np.sqrt(float((own**2).sum())))))
        return found

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cosine = [best(np.asarray(a.values, np.int64), np.asarray(b.values, np.int64)) for a, b in zip(batch.column("__a"), batch.column("__b"), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("item_id"), pa.array(cosine, pa.float64())], ["doc_id", "item_id", "cosine"])

    return run


def chunked_contamination(docs: DataFrame, benchmark: DataFrame, n: int = 3, threshold: float = COSINE) -> DataFrame:
    """(doc_id, item_id, cosine) of records with a window of an item's length whose counts of word n-grams lie above the threshold.

    A pair is looked at only if the grams that the whole record shares with the item hold more than the threshold's
    square of the item's squared norm, which every pair above the threshold does. Texts without an n-gram match nothing.
    """
    listed = gram_hashes(tokens(F.col("text")), n)
    items = benchmark.select("item_id", listed.alias("__b")).filter(F.size("__b") > 0)
    counts = items.select("item_id", F.explode("__b").alias("gram")).groupBy("item_id", "gram").agg(F.pow(F.count(F.lit(1)), F.lit(2)).alias("square"))
    held = counts.join(counts.groupBy("item_id").agg(F.sum("square").alias("norm")), "item_id")
    texts = cut(docs.select("doc_id", listed.alias("__a")))
    met = texts.select("doc_id", F.explode(F.array_distinct("__a")).alias("gram")).join(broadcast_side(held), "gram")
    near = met.groupBy("doc_id", "item_id").agg(F.sum("square").alias("part"), F.max("norm").alias("norm")).filter(F.col("part") >= threshold * threshold * F.col("norm") - 1e-9)
    pairs = near.select("doc_id", "item_id").join(texts, "doc_id").join(items, "item_id").select("doc_id", "item_id", "__a", "__b")
    return map_arrow(pairs, _best_windows(threshold), "doc_id long, item_id long, cosine double").filter(F.col("cosine") > threshold)


def combine_rejections(lexical: DataFrame, semantic: DataFrame, key: str) -> DataFrame:
    """(id, lexical, semantic) of the ids that a rule rejects."""
    both = lexical.select(key, F.lit(True).alias("l"), F.lit(False).alias("s")).unionByName(semantic.select(key, F.lit(False).alias("l"), F.lit(True).alias("s")))
    return both.groupBy(key).agg(F.bool_or("l").alias("lexical"), F.bool_or("s").alias("semantic"))


def _rows(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(len(column), -1)


def _units(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors, and their first ``HEAD`` numbers with the length of the rest, whose products bound the cosines from above."""
    size = np.linalg.norm(x, axis=1)
    unit = x / np.where(size > 0, size, 1)[:, None]
    return unit, np.column_stack([unit[:, :HEAD], np.linalg.norm(unit[:, HEAD:], axis=1)]).astype(np.float32)


def _above(ids: pa.Array, units: np.ndarray, key: str, own: int, threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, heads = _units(units)
        names = np.asarray(ids.to_numpy(zero_copy_only=False))
        for batch in batches:
            if not batch.num_rows:
                continue
            mine, part = batch.column(key).to_numpy(zero_copy_only=False), np.asarray(batch.column("__part"))
            x, bounds = _units(_rows(batch.column("embedding")))
            a, b, cosine = [], [], []
            for at in range(0, len(x), PRODUCT_ROWS):
                r, c = np.nonzero(bounds[at : at + PRODUCT_ROWS] @ heads.T > threshold - 1e-4)
                r = r + at
                # the pairs inside the block once
                once = (part[r] != own) | (mine[r] > names[c])
                r, c = r[once], c[once]
                for k in range(0, len(r), PRODUCT_ROWS * 16):
                    p, q = r[k : k + PRODUCT_ROWS * 16], c[k : k + PRODUCT_ROWS * 16]
                    dots = np.einsum("ij,ij->i", x[p], units[q])
                    p, q, dots = p[dots > threshold], q[dots > threshold], dots[dots > threshold]
                    a.append(np.minimum(mine[p], names[q]))
                    b.append(np.maximum(mine[p], names[q]))
                    cosine.append(dots)
            if a:
                kind = batch.schema.field(key).type
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a), kind), pa.array(np.concatenate(b), kind), pa.array(np.concatenate(cosine))], ["a", "b", "cosine"])

    return run


def similar_vectors(vectors: DataFrame, key: str, threshold: float = COSINE, block: int = BLOCK_ITEMS) -> DataFrame:
    """(a, b, cosine): all pairs of distinct vectors above the threshold, and each vector's smallest id with its copies.

    Compared exactly, one block of vectors after another with all rows of its own and the later blocks; the work is
    the square of the distinct vectors. Vectors of zeros have no cosine and no pair.
    """
    kind = vectors.schema[key].dataType.simpleString()
    some = cut(vectors.select(key, "embedding").filter(F.exists("embedding", lambda x: x != 0)))
    coded = some.select(key, F.xxhash64("embedding").alias("h"), F.xxhash64(F.lit(1), "embedding").alias("g"))
    first = coded.groupBy("h", "g").agg(F.min(key).alias("a"))
    told = cut(coded.join(first, ["h", "g"]).select("a", F.col(key).alias("b")))
    out = told.filter("a <> b").select("a", "b", F.lit(1.0).alias("cosine"))
    heads = told.filter("a = b")
    blocks = max(1, -(-heads.count() // block))
    shaped = cut(some.join(heads.select(F.col("a").alias(key)), key, "left_semi").withColumn("__part", F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int")))
    for own in range(blocks):
        held = shaped.filter(F.col("__part") == own).select(key, "embedding").toArrow().combine_chunks()
        if held.num_rows:
            column = held.column("embedding").combine_chunks()
            run = _above(held.column(key).combine_chunks(), _units(_rows(column))[0], key, own, threshold)
            out = out.unionByName(cut(map_arrow(shaped.filter(F.col("__part") >= own), run, f"a {kind}, b {kind}, cosine double")))
    return out


def strict_pool(docs: DataFrame, n: int = 15, threshold: float = COSINE) -> DataFrame:
    """Ids that survive 15-gram containment and cosine similarity inside the pool (pair semantics); texts without words stay."""
    lexical = overlap_pairs(docs, "doc_id", "text", n).select("a", "b")
    semantic = similar_vectors(encode(docs, "doc_id", "text", d=256), "doc_id", threshold).select("a", "b")
    gone = lexical.unionByName(semantic).select(F.col("b").alias("doc_id")).distinct()
    return docs.select("doc_id").join(gone, "doc_id", "left_anti")
