"""Streaming queries, drained once, against batch oracles."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from sparkcurate.functions.lineage import shared_folder
from sparkcurate.plans import oracle_text as o
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import table
from sparkcurate.streaming import stream as st

_AT = "yyyy-MM-dd HH:mm:ss"


@query("st_tumbling", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def tumbling(spark, d):
    return st.drain(st.tumbling(st.stream_table(spark, d, "events"))).select(F.date_format("w.start", _AT).alias("start"), "event_type", "n", "total")


@query("st_sliding", "SELECT strftime(date_trunc('day', ts) - to_days(k), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) WHERE true GROUP BY ALL")
def sliding(spark, d):
    return st.drain(st.sliding(st.stream_table(spark, d, "events"))).select(F.date_format("w.start", _AT).alias("start"), "n")


@query("st_sessions", """WITH e AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events), s AS (SELECT *, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, strftime(date_trunc('second', min(ts)), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def sessions(spark, d):
    return st.drain(st.sessions(st.stream_table(spark, d, "events"))).select("user_id", F.date_format("w.start", _AT).alias("start"), "n")


@query("st_distinct", "SELECT count(DISTINCT event_id) AS n FROM events")
def distinct(spark, d):
    return st.drain(st.distinct_events(st.stream_table(spark, d, "events")).select("event_id"), "append").agg(F.count(F.lit(1)).alias("n"))


@query("st_decontaminate", f"WITH {o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)} SELECT doc_id, count(*) AS hits FROM dg WHERE gram IN (SELECT gram FROM bg) GROUP BY doc_id")
def decontaminate(spark, d):
    return st.drain(st.decontaminate_stream(st.stream_table(spark, d, "documents"), table(spark, d, "benchmark")))


@query("st_append_closed_windows", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 2 DAY FROM events) GROUP BY ALL")
def append_closed(spark, d):
    return st.drain(st.tumbling(st.stream_table(spark, d, "events")), "append").select(F.date_format("w.start", _AT).alias("start"), "event_type", "n", "total")


@query("st_quota_sink", "SELECT event_type, event_id FROM (SELECT event_type, event_id, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS k FROM events) WHERE k <= 5")
def quota_sink(spark, d):
    """The first rows of each category over all batches, merged batch by batch into a file sink."""
    path = f"{shared_folder(spark)}/quota-{uuid.uuid4().hex}"
    rows = st.stream_table(spark, d, "events").select("event_type", "event_id", "value")
    return st.fill_quota(rows, path, "event_type", [F.desc("value"), F.col("event_id")], 5).select("event_type", "event_id")


@query("st_stateful_quota", "SELECT event_type, least(count(*), 50) AS accepted FROM events GROUP BY event_type")
def stateful_quota(spark, d):
    """A quota in keyed state: rows are accepted until a category has its share."""
    rows = st.stream_table(spark, d, "events").select("event_type", "event_id")
    return st.drain(st.accept_within_quota(rows, "event_type", "event_id", 50), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("accepted"))


@query("st_progress", "SELECT (SELECT count(*) FROM events) AS read, 0 AS late")
def progress(spark, d):
    """Rows read and rows dropped behind the watermark, from the stream's own progress; one file holds all, so none is late."""
    told = st.drained_progress(st.tumbling(st.stream_table(spark, d, "events")), "append")
    return spark.createDataFrame([told], "read long, late int")
