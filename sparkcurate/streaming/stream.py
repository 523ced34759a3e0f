"""Streaming forms: windows with watermarks, late rows, deduplication, decontamination, per-category quotas.

Defined cases: events without a time are behind every watermark and in no window; rows later than the watermark allows
are dropped and counted in the progress; repeated events are kept once inside it; null categories have a quota of
their own; an empty stream gives no rows.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sparkcurate.functions.arrow import ship_package
from sparkcurate.functions.lineage import is_folder, shared_folder
from sparkcurate.functions.text import grams
from sparkcurate.operators.decontam import broadcast_side
from sparkcurate.operators.select import top_per_group


def stream_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, one file or a folder of files, as a file stream with its explicit schema; ``ts`` becomes a timestamp so that it can carry a watermark."""
    path = f"{sf_dir}/{name}.parquet"
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    # a stream reads folders only: one file is picked from the folder that holds it
    parent, _, leaf = path.rpartition("/")
    rows = reader.parquet(path) if is_folder(spark, path) else reader.option("pathGlobFilter", leaf).parquet(parent)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs the stream over what is there and returns its result; the rows lie in the shared folder and never in the driver."""
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/drained-{uuid.uuid4().hex}"
    written: list[int] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/v{number}")
        written.append(number)

    query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    if not written:
        return spark.createDataFrame([], stream.schema)
    # in complete mode each batch holds the whole result
    return spark.read.schema(stream.schema).parquet(*[f"{path}/v{n}" for n in (written[-1:] if mode == "complete" else dict.fromkeys(written))])


def drained_progress(stream: DataFrame, mode: str = "complete") -> tuple[int, int]:
    """Runs the stream over what is there; (rows read, rows dropped behind the watermark)."""
    folder = f"{shared_folder(stream.sparkSession)}/progress-{uuid.uuid4().hex}"
    query = stream.writeStream.format("noop").outputMode(mode).option("checkpointLocation", folder).trigger(availableNow=True).start()
    query.awaitTermination()
    steps = query.recentProgress
    return sum(p.numInputRows for p in steps), sum(s.numRowsDroppedByWatermark for p in steps for s in p.stateOperators)


def tumbling(events: DataFrame, size: str = "1 day", late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 days").groupBy(F.window("ts", size, step).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    return events.withWatermark("ts", "2 days").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def distinct_events(events: DataFrame, late: str = "2 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def decontaminate_stream(docs: DataFrame, benchmark: DataFrame, n: int = 15) -> DataFrame:
    """(doc_id, hit grams) of streamed documents against the static benchmark, broadcast up to a bound."""
    held = broadcast_side(grams(benchmark, "item_id", "text", n).select("gram").distinct())
    return grams(docs, "doc_id", "text", n).join(held, "gram").groupBy("doc_id").agg(F.count(F.lit(1)).alias("hits"))


def quota_sink(path: str, group: str, order: list, quota: int):
    """``foreachBatch`` function that keeps the first rows of each group over all batches; repeated batches change nothing.

    Every batch writes a new version beside the last one, so a failed batch leaves the last version whole.
    """

    def run(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        held = batch if number == 0 else spark.read.parquet(f"{path}/v{number - 1}").unionByName(batch)
        top_per_group(held.dropDuplicates(), [group], order, quota).drop("rn").write.mode("overwrite").parquet(f"{path}/v{number}")

    return run


def fill_quota(stream: DataFrame, path: str, group: str, order: list, quota: int) -> DataFrame:
    """Runs the stream over what is there into a quota sink and returns its last version."""
    query = stream.writeStream.foreachBatch(quota_sink(path, group, order, quota)).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    last = max((p.batchId for p in query.recentProgress if p.numInputRows), default=None)
    spark = stream.sparkSession
    return spark.createDataFrame([], stream.schema) if last is None else spark.read.parquet(f"{path}/v{last}")


def accept_within_quota(stream: DataFrame, group: str, key: str, quota: int) -> DataFrame:
    """(group, key) of the rows that arrive before their group has its quota; the state is one count a group."""
    ship_package(stream.sparkSession)
    kinds = {f.name: f.dataType.simpleString() for f in stream.schema}

    def accept(name, batches, state: GroupState):
        used = state.get[0] if state.exists else 0
        for rows in batches:
            some = rows.sort_values(key).head(quota - used)
            used += len(some)
            if len(some):
                yield some[[group, key]]
        state.update((used,))

    return stream.groupBy(group).applyInPandasWithState(accept, f"{group} {kinds[group]}, {key} {kinds[key]}", "used long", "append", GroupStateTimeout.NoTimeout)
