"""Question vectors, clustering and assignment.

Defined cases: null and empty texts, and texts without words, have a vector of zeros; ties between centroids go to the
lowest; with fewer distinct vectors than clusters some stay empty; equal rows are assigned alike; an empty table has no
assignment (fitting one raises); other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow, ship_package
from sparkcurate.functions.text import hex_number, tokens

DIMENSIONS = 1024
FIT_SAMPLE = 1_000_000


def encode_md5(df: DataFrame, key: str, text_col: str, d: int) -> DataFrame:
    """(id, v): signed token counts over d buckets of the tokens' MD5; whole numbers, equal in every engine.

    One aggregate over distinct tokens, one over buckets; records without tokens have zeros.
    """
    each = df.select(key, F.explode(tokens(F.col(text_col))).alias("w")).groupBy(key, "w").agg(F.count(F.lit(1)).alias("c"))
    digest = F.md5("w")
    sign = F.when(hex_number(digest, 8, 1) % 2 == 0, 1).otherwise(-1)
    placed = each.select(key, (hex_number(digest, 1, 7) % d).alias("slot"), (sign * F.col("c")).alias("x"))
    sums = placed.groupBy(key).agg(F.array(*[F.coalesce(F.sum(F.when(F.col("slot") == i, F.col("x"))), F.lit(0)) for i in range(d)]).alias("v"))
    return df.select(key).join(sums, key, "left").select(key, F.coalesce("v", F.array(*[F.lit(0).cast("long")] * d)).alias("v"))


def _encode(key: str, d: int, n: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import re
        import zlib

        split = re.compile(r"[^\W_]+", re.UNICODE)
        for batch in batches:
            out = np.zeros((batch.num_rows, d), np.float32)
            for i, text in enumerate(batch.column("__text").to_pylist()):
                words = split.findall((text or "").lower())
                spans = [" ".join(words[j : j + n]) for j in range(max(len(words) - n + 1, min(len(words), 1)))]
                hashes = np.array([zlib.crc32(s.encode(), seed) for s in spans], np.int64)
                np.add.at(out[i], hashes % d, np.where((hashes >> 20) & 1, 1.0, -1.0))
                size = np.linalg.norm(out[i])
                out[i] /= size if size else 1
            yield pa.RecordBatch.from_arrays([batch.column(key), pa.array(list(out), pa.list_(pa.float32()))], [key, "embedding"])

    return run


def encode(df: DataFrame, key: str, text_col: str, d: int = DIMENSIONS, n: int = 3, seed: int = 42) -> DataFrame:
    """(id, embedding): unit vectors of signed hashed word n-grams."""
    shaped = df.select(key, F.col(text_col).alias("__text"))
    return map_arrow(shaped, _encode(key, d, n, seed), f"{key} {df.schema[key].dataType.simpleString()}, embedding array<float>")


def assign(df: DataFrame, centroids: DataFrame, key: str, vec_col: str = "embedding") -> DataFrame:
    """(id, cluster, dist): nearest centroid by squared distance in double, ties to the lowest; centroids are broadcast."""
    pairs = df.select(key, F.col(vec_col).alias("__v")).join(F.broadcast(centroids.select("cluster", F.col("center").alias("__c"))))
    dist = F.aggregate(F.zip_with("__v", "__c", lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    return pairs.select(key, "cluster", dist.alias("dist")).groupBy(key).agg(F.min(F.struct("dist", "cluster")).alias("best")).select(key, F.col("best.cluster").alias("cluster"), F.col("best.dist").alias("dist"))


def _nearest(centers: np.ndarray, ids: np.ndarray, key: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array(batch.column("__v").to_pylist(), np.float64).reshape(batch.num_rows, -1)
            d = ((x**2).sum(1)[:, None] - 2 * x @ centers.T + (centers**2).sum(1)[None, :]) if batch.num_rows else np.zeros((0, len(centers)))
            at = d.argmin(axis=1) if batch.num_rows else np.zeros(0, int)
            yield pa.RecordBatch.from_arrays([batch.column(key), pa.array(ids[at].astype(np.int32)), pa.array(np.maximum(d[np.arange(len(at)), at], 0))], [key, "cluster", "dist"])

    return run


def assign_batched(df: DataFrame, centroids: DataFrame, key: str, vec_col: str = "embedding") -> DataFrame:
    """As ``assign`` by matrix products of Arrow batches; no row is multiplied by the centroids."""
    rows = centroids.orderBy("cluster").collect()
    centers, ids = np.array([r["center"] for r in rows], np.float64), np.array([r["cluster"] for r in rows])
    return map_arrow(df.select(key, F.col(vec_col).alias("__v")), _nearest(centers, ids, key), f"{key} {df.schema[key].dataType.simpleString()}, cluster int, dist double")


def lloyd_step(df: DataFrame, assigned: DataFrame, key: str, vec_col: str = "embedding") -> DataFrame:
    """(cluster, dim, value): means of the assigned vectors, one partial aggregate over dimensions."""
    each = df.select(key, F.posexplode(vec_col).alias("dim", "x")).join(assigned.select(key, "cluster"), key)
    return each.groupBy("cluster", "dim").agg(F.avg(F.col("x").cast("double")).alias("value"))


def _k_means(vectors: DataFrame, k: int, seed: int) -> list:
    from pyspark.ml.clustering import KMeans

    return KMeans(k=k, seed=seed, featuresCol="features").fit(vectors).clusterCenters()


def _bisecting(vectors: DataFrame, k: int, seed: int) -> list:
    from pyspark.ml.clustering import BisectingKMeans

    return BisectingKMeans(k=k, seed=seed, featuresCol="features").fit(vectors).clusterCenters()


def _mixture(vectors: DataFrame, k: int, seed: int) -> list:
    from pyspark.ml.clustering import GaussianMixture

    return [r["mean"].toArray() for r in GaussianMixture(k=k, seed=seed, featuresCol="features").fit(vectors).gaussiansDF.collect()]


Algorithm = Callable[[DataFrame, int, int], list]
_algorithms: dict[str, Algorithm] = {"kmeans": _k_means, "bisecting": _bisecting, "mixture": _mixture}


def register_algorithm(name: str, algorithm: Algorithm) -> None:
    """An algorithm takes (a frame with ``features`` vectors, k, seed) and returns the centres."""
    _algorithms[name] = algorithm


def cluster(df: DataFrame, key: str, k: int, vec_col: str = "embedding", seed: int = 42, algo: str = "kmeans") -> tuple[DataFrame, DataFrame]:
    """(assignment, centroids): fitted by a registered algorithm on at most FIT_SAMPLE rows, assigned for all."""
    from pyspark.ml.functions import array_to_vector

    rows = df.count()
    some = df if rows <= FIT_SAMPLE else df.filter(F.pmod(F.xxhash64(key), F.lit(1 << 20)) < int((1 << 20) * FIT_SAMPLE / rows))
    vectors = some.select(array_to_vector(F.col(vec_col).cast("array<double>")).alias("features"))
    centers = [(i, [float(x) for x in c]) for i, c in enumerate(_algorithms[algo](vectors, k, seed))]
    centroids = df.sparkSession.createDataFrame(centers, "cluster int, center array<double>")
    return assign_batched(df, centroids, key, vec_col), centroids


def cluster_hierarchical(df: DataFrame, key: str, k1: int, k2: int, vec_col: str = "embedding", seed: int = 42, cell_sample: int = 10_000) -> DataFrame:
    """Two levels for many clusters: k1 coarse cells, then k2 clusters fitted inside each on a bounded sample."""
    coarse, _ = cluster(df, key, k1, vec_col, seed)
    joined = df.select(key, F.col(vec_col).alias("v")).join(coarse.select(key, F.col("cluster").alias("cell")), key)
    sizes = joined.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))
    some = joined.join(F.broadcast(sizes), "cell").filter(F.pmod(F.xxhash64(key), F.lit(1 << 20)) < F.lit(float(1 << 20) * cell_sample) / F.col("n"))
    ship_package(df.sparkSession)

    def fit(rows: pd.DataFrame) -> pd.DataFrame:
        x = np.array(rows.sort_values(key)["v"].tolist(), np.float64)
        rng = np.random.default_rng(seed)
        centers = x[rng.permutation(len(x))[: min(k2, len(x))]]
        for _ in range(12):
            at = ((x[:, None, :] - centers[None]) ** 2).sum(-1).argmin(1) if len(x) * len(centers) < 2_000_000 else np.concatenate([((p[:, None, :] - centers[None]) ** 2).sum(-1).argmin(1) for p in np.array_split(x, 64)])
            centers = np.stack([x[at == c].mean(0) if (at == c).any() else centers[c] for c in range(len(centers))])
        return pd.DataFrame({"cell": int(rows["cell"].iloc[0]), "sub": np.arange(len(centers)), "center": list(centers)})

    fine = some.groupBy("cell").applyInPandas(fit, "cell int, sub int, center array<double>")
    pairs = joined.join(F.broadcast(fine), "cell")
    dist = F.aggregate(F.zip_with("v", "center", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, t: s + t)
    best = pairs.select(key, "cell", "sub", dist.alias("d")).groupBy(key).agg(F.min(F.struct("d", "cell", "sub")).alias("b"))
    return best.select(key, (F.col("b.cell") * k2 + F.col("b.sub")).cast("int").alias("cluster"))
