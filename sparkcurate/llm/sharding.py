"""Sharding by jump consistent hashing (DataFrame functions only).

A key's shard is found by the published jump walk: a 64-bit linear congruential generator seeded
with the key jumps forward over shard numbers; the last jump that stays below the shard count is
the shard. No ring table exists, and with one more shard a row either stays or moves to it.

Slots are gapless positions inside a shard in the order (doc_id, text_crc32, size). They are made
without ever gathering a shard in one task: doc_id quantiles (a bounded list, at most
``MAX_QUANTILES``) cut the key space into chunks, a doc_id that is itself a quantile gets chunks
of its own which are split again by the text checksum, equal rows are counted before they move, and
only the per-chunk counts are summed up over a shard.

Defined cases: a null doc_id takes key 0 and sorts first; null text has size 1 and checksum 0; empty
tables give no rows; repeated rows each get a slot; columns beyond doc_id and text are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# Fixed values of the published generator.
MULTIPLIER = 2862933555777941757
MODULUS = 18446744073709551616
SHIFT = 8589934592

CHUNK_ROWS = 4096
MAX_QUANTILES = 4096


def jump_shard(key: Column, shards: int) -> Column:
    """Shard (0 .. shards - 1) of an integer key."""
    unsigned = F.when(key < 0, key.cast("decimal(20,0)") + F.lit(str(MODULUS)).cast("decimal(20,0)")).otherwise(key.cast("decimal(20,0)"))

    def step(acc: Column, _: Column) -> Column:
        drawn = ((acc["k"] * F.lit(str(MULTIPLIER)).cast("decimal(19,0)") + F.lit(1).cast("decimal(1,0)")) % F.lit(str(MODULUS)).cast("decimal(20,0)")).cast("decimal(20,0)")
        high = F.floor(drawn / F.lit(SHIFT).cast("decimal(10,0)"))
        jumped = F.floor((acc["j"] + 1).cast("double") * (F.lit(2147483648.0) / (high.cast("double") + 1.0))).cast("long")
        return F.when(acc["j"] < shards, F.struct(drawn.alias("k"), acc["j"].alias("b"), jumped.alias("j"))).otherwise(acc)

    start = F.struct(unsigned.cast("decimal(20,0)").alias("k"), F.lit(-1).cast("long").alias("b"), F.lit(0).cast("long").alias("j"))
    walked = F.aggregate(F.sequence(F.lit(1), F.lit(shards + 1)), start, step)
    return F.when(walked["j"] < shards, walked["j"]).otherwise(walked["b"]).cast("int")


def _position(bounds: list[int], key: Column) -> Column:
    """Index of the last bound that is <= key (-1 if none), by binary search in an array literal."""
    array, low, width = F.array(*[F.lit(b).cast("long") for b in bounds]), F.lit(-1), 1
    while width < len(bounds) + 1:
        width *= 2
    steps = []
    while width > 1:
        width //= 2
        steps.append(width)
    return F.aggregate(
        F.array(*[F.lit(s) for s in steps]) if steps else F.array(F.lit(1)),
        low,
        lambda at, s: F.when((at + s < len(bounds)) & (F.get(array, at + s) <= key), at + s).otherwise(at),
    )


def key_quantiles(docs: DataFrame, column: str, rows_per_chunk: int = CHUNK_ROWS) -> list[int]:
    """At most MAX_QUANTILES sorted values of a long column; reads that column alone."""
    rows = docs.select(column).count()
    parts = min(MAX_QUANTILES, -(-rows // rows_per_chunk))
    if parts < 2:
        return []
    found = docs.select(F.percentile_approx(F.coalesce(F.col(column), F.lit(0)), [i / parts for i in range(1, parts)], 20 * MAX_QUANTILES)).first()[0]
    return sorted(set(found or []))


def assign_shards(docs: DataFrame, shards: int = 16, rows_per_chunk: int = CHUNK_ROWS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row."""
    text = F.coalesce(F.col("text"), F.lit(""))
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    key = F.coalesce(F.col("doc_id"), F.lit(0).cast("long"))
    bounds = key_quantiles(docs.select(F.col("doc_id").cast("long").alias("doc_id")), "doc_id", rows_per_chunk)
    if bounds:
        at = _position(bounds, key)
        placed = sized.withColumn("__at", at)
        array = F.array(*[F.lit(b).cast("long") for b in bounds])
        own = F.col("doc_id").isNotNull() & (F.get(array, F.col("__at")) == key)
        placed = placed.withColumn("__chunk", F.when(F.col("doc_id").isNull(), -2).otherwise(2 * F.col("__at") + F.when(own, 0).otherwise(1))).withColumn("__sub", F.when(own | F.col("doc_id").isNull(), F.shiftright("text_crc32", 24)).otherwise(0).cast("int"))
    else:
        placed = sized.withColumn("__chunk", F.lit(0)).withColumn("__sub", F.lit(0))
    placed = placed.withColumn("shard", jump_shard(key, shards))
    counted = placed.groupBy("shard", "__chunk", "__sub", "doc_id", "text_crc32", "size").agg(F.count(F.lit(1)).alias("__n"))
    chunk = ["shard", "__chunk", "__sub"]
    totals = counted.groupBy(*chunk).agg(F.sum("__n").alias("__rows"))
    before = Window.partitionBy("shard").orderBy("__chunk", "__sub").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.withColumn("__offset", F.coalesce(F.sum("__rows").over(before), F.lit(0))).drop("__rows")
    inside = Window.partitionBy(*chunk).orderBy("doc_id", "text_crc32", "size").rowsBetween(Window.unboundedPreceding, -1)
    local = counted.withColumn("__local", F.coalesce(F.sum("__n").over(inside), F.lit(0)))
    # rows lie by chunk already, so only the few offsets move
    joined = local.join(offsets.hint("shuffle_hash"), chunk)
    first = F.col("__offset") + F.col("__local")
    return joined.withColumn("slot", F.explode(F.sequence(first, first + F.col("__n") - 1))).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", F.col("slot").cast("long").alias("slot"),
        jump_shard(F.coalesce(F.col("doc_id"), F.lit(0).cast("long")), shards + 1).alias("grown_shard"),
    )
