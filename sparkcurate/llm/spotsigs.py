"""SpotSigs document fingerprints.

A spot is a common word (the anchor) with the chain of the next ``CHAIN`` content words after it; a
fingerprint is the set of a text's spots, each a 32-bit hash, written as sorted hexadecimal numbers.
Likeness is the Jaccard similarity of two fingerprints. For a join, fingerprints are partitioned by set
length so that partners lie in one or two neighbouring partitions, only each set's rarest spots are looked
up, and the exact similarity decides.

``fingerprint_neighbours`` also compares each document with the next one in falling order of doc_id and with
its own text after an edit. Documents travel once, to chunks between doc_id quantiles; a doc_id that is a quantile
itself (null doc_ids may be) has chunks of its own, dealt by the text's hash, which is the order inside it. The largest
document of a chunk (one a chunk, a bounded list) also goes to the chunk above it.

Defined cases: null text is empty; a text with words but no spot has one spot of all its words; a text
without words has an empty fingerprint, and two empty ones have likeness 1; null doc_ids come last in
falling order; rows of equal doc_id follow the order of their texts' hashes; a single document is its
own successor; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.llm.sharding import _position, key_quantiles
from sparkcurate.llm.textscan import U, Words, distinct_by_row, mix, slices, text_bytes

CHAIN = 2
CHUNK_ROWS = 512
SMALLEST = -(1 << 63)

# Common words of English, French, German and Spanish that anchor spots.
ANCHORS = (
    "a an the of and or to in on at by for from with as is are was were be been it its this that these those he she they we you i his her their not but have has had "
    "le la les un une des du de et ou dans sur par pour avec est sont était être ce cette ces il elle ils elles nous vous ne pas que qui au aux en "
    "der die das den dem des ein eine einer einen und oder im mit von zu für auf ist sind war sein es sie er wir ihr nicht als auch an aus bei "
    "el los las una unos unas y o del al por para con es son era ser se lo su sus que no como más"
).split()


def _anchor_hashes() -> np.ndarray:
    data, offsets = text_bytes(pa.array([" ".join(sorted(set(ANCHORS)))]))
    return np.sort(Words(data, offsets).hash)


def spots(column: pa.Array, chain: int = CHAIN) -> tuple[np.ndarray, np.ndarray]:
    """Distinct spots of each row: (hashes, rows), sorted by row and hash."""
    words = Words(*text_bytes(column))
    anchors = _anchor_hashes()
    common = anchors[np.minimum(np.searchsorted(anchors, words.hash), len(anchors) - 1)] == words.hash
    content, at = np.flatnonzero(~common), np.flatnonzero(common)
    after = np.searchsorted(content, at)
    whole = after + chain <= len(content)
    at, after = at[whole], after[whole]
    if len(at):
        whole = words.row[content[after + chain - 1]] == words.row[at]
        at, after = at[whole], after[whole]
    found = words.hash[at]
    for c in range(chain):
        found = mix(found * U(0x9E3779B97F4A7C15) + words.hash[content[after + c]])
    rows = words.row[at]
    count = np.bincount(rows, minlength=len(column))
    bare = np.flatnonzero((count == 0) & (words.count > 0))
    if len(bare):
        starts = words.first[bare]
        position = np.arange(len(words.hash)) - np.repeat(words.first[:-1], words.count)
        all_words = np.add.reduceat(mix(words.hash + position.astype(np.uint64)), words.first[:-1][words.count > 0])
        extra = all_words[np.cumsum(words.count > 0)[bare] - 1]
        assert len(extra) == len(starts)
        found, rows = np.concatenate([found, mix(extra)]), np.concatenate([rows, bare])
    return distinct_by_row((found >> U(32)), rows)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def _hexadecimal(spot: np.ndarray) -> str:
    return spot.astype(">u4").tobytes().hex()


def _fingerprints(chain: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            found, rows = spots(batch.column("text"), chain)
            first = np.zeros(batch.num_rows + 1, np.int32)
            first[1:] = np.cumsum(np.bincount(rows, minlength=batch.num_rows))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(first), pa.array(found.astype(np.int64)))], ["doc_id", "spots"])

    return run


def fingerprints(docs: DataFrame, chain: int = CHAIN) -> DataFrame:
    """doc_id and its spots (sorted 32-bit hashes)."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_arrow(texts, _fingerprints(chain), "doc_id long, spots array<bigint>")


def similar_pairs(docs: DataFrame, threshold: float = 0.8, chain: int = CHAIN) -> tuple[DataFrame, DataFrame]:
    """(pairs of class representatives with their likeness, doc_id -> representative).

    Documents with equal fingerprints are one class. A set is split into rare and common spots by document
    frequency; two sets of the wanted likeness share one of their rarest ``n - ceil(t n) + 1`` spots.
    """
    prints = fingerprints(docs, chain).withColumn("print", F.md5(F.concat_ws(",", F.transform("spots", lambda s: s.cast("string")))))
    classes = prints.groupBy("print").agg(F.min("doc_id").alias("member"), F.first("spots").alias("spots"))
    members = prints.select("doc_id", "print").join(classes.select("print", "member"), "print").select("doc_id", "member")
    sets = classes.select("member", "spots", F.size("spots").alias("n")).filter("n > 0")
    each = sets.select("member", "n", F.explode("spots").alias("spot"))
    rarity = each.groupBy("spot").agg(F.count(F.lit(1)).alias("df")).filter("df > 1")
    ordered = each.join(rarity, "spot", "left").groupBy("member", "n").agg(F.array_sort(F.collect_list(F.struct(F.coalesce("df", F.lit(1)).alias("df"), "spot"))).alias("order"))
    prefix = F.col("n") - F.ceil(F.col("n") * threshold - 1e-9).cast("int") + 1
    step = F.floor(F.log("n") / F.lit(-np.log(threshold))).cast("int")
    heads = ordered.withColumn("head", F.explode(F.slice("order", F.lit(1), prefix))).filter("head.df > 1").select("member", "n", F.col("head.spot").alias("spot"), step.alias("part"))
    left = heads.select(F.col("member").alias("a"), F.col("n").alias("na"), "spot", F.explode(F.array(F.col("part"), F.col("part") + 1)).alias("part"))
    right = heads.select(F.col("member").alias("b"), F.col("n").alias("nb"), "spot", "part")
    fits = (F.col("na") < F.col("nb")) | ((F.col("na") == F.col("nb")) & (F.col("a") < F.col("b")))
    near = left.join(right, ["spot", "part"]).filter(fits & (F.col("na") >= F.col("nb") * threshold - 1e-9)).select("a", "b").distinct()
    sized = near.join(sets.select(F.col("member").alias("a"), F.col("spots").alias("sa")), "a").join(sets.select(F.col("member").alias("b"), F.col("spots").alias("sb")), "b")
    both = F.size(F.array_intersect("sa", "sb"))
    scored = sized.select("a", "b", (both / (F.size("sa") + F.size("sb") - both)).alias("likeness"))
    return scored.filter(F.col("likeness") >= threshold - 1e-12), members


def _neighbours(chain: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def pairs(rows: list[tuple]) -> pa.RecordBatch | None:
            """Rows are consecutive; each but the last is answered if it is no helper and has its successor behind it."""
            texts = [r[2] for r in rows]
            asked = [i for i in range(len(rows) - 1) if not rows[i][3] and rows[i][0] == rows[i + 1][0]]
            if not asked:
                return None
            edited = []
            for i in asked:
                n = len(texts[i])
                edited.append(texts[i][: n - n // 3] + texts[i + 1][: n // 3])
            found, at = spots(pa.array(texts + edited, pa.large_string()), chain)
            first = np.searchsorted(at, np.arange(len(texts) + len(edited) + 1))
            spot = [found[first[x] : first[x + 1]] for x in range(len(texts) + len(edited))]
            out = [
                (rows[i][1], len(texts[i]), hashlib.sha256(edited[x].encode()).hexdigest(), _hexadecimal(spot[i]), _hexadecimal(spot[len(texts) + x]), likeness(spot[i], spot[len(texts) + x]), likeness(spot[i], spot[i + 1]))
                for x, i in enumerate(asked)
            ]
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

        for batch in slices(batches):
            rows = held + list(zip(*(batch.column(c).to_pylist() for c in ("chunk", "doc_id", "text", "helper")), strict=True))
            made = pairs(rows)
            if made is not None:
                yield made
            held = rows[-1:]

    return run


def fingerprint_neighbours(docs: DataFrame, chain: int = CHAIN, chunk_rows: int = CHUNK_ROWS) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of every row."""
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(SMALLEST))
    bounds = key_quantiles(docs.select(key.alias("doc_id")), "doc_id", chunk_rows)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    chunk: Column = F.lit(0).cast("long")
    if bounds:
        at = _position(bounds, F.col("key"))
        own = (at >= 0) & (F.get(F.array(*[F.lit(b).cast("long") for b in bounds]), at) == F.col("key"))
        # in the order of (key, told): an own key's parts come before the keys above it
        chunk = (at.cast("long") * 2 + F.when(own, 0).otherwise(1)) * 256 + F.when(own, F.shiftright("told", 56) + 128).otherwise(0)
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), key.alias("key"), text.alias("text"), F.xxhash64(text).alias("told")).withColumn("chunk", chunk)
    # one row a chunk, at most as many as there are quantiles
    tops = base.groupBy("chunk").agg(F.max(F.struct("key", "told")).alias("top")).orderBy("chunk").collect()
    above = [(r["top"]["key"], r["top"]["told"], tops[(i + 1) % len(tops)]["chunk"]) for i, r in enumerate(tops)]
    heads = docs.sparkSession.createDataFrame(above, "key long, told long, above int")
    marked = base.join(F.broadcast(heads), ["key", "told"], "left")
    mine = F.array(F.struct(F.col("chunk").alias("c"), F.lit(False).alias("h")))
    sent = F.when(F.col("above").isNull(), mine).otherwise(F.concat(mine, F.array(F.struct(F.col("above").alias("c"), F.lit(True).alias("h")))))
    dealt = marked.withColumn("to", F.explode(sent)).select(F.col("to.c").alias("chunk"), F.col("to.h").alias("helper"), "doc_id", "key", "told", "text")
    placed = dealt.repartition("chunk").sortWithinPartitions("chunk", "helper", F.desc("key"), F.desc("told")).select("chunk", "doc_id", "text", "helper")
    return map_arrow(placed, _neighbours(chain), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
