"""Evaluation and audit measures, and the workloads around them."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparkcurate.functions.text import MARKERS, domain_of_source, marker_counts, n_tokens
from sparkcurate.operators import evaluate as ev
from sparkcurate.operators.decontam import contaminated_any
from sparkcurate.operators.rules import filter_complete, filter_language, heuristic_scores
from sparkcurate.plans import oracle_text as o
from sparkcurate.plans.queries_select import _RUNS
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import table

_AVG = f"""{_RUNS}, lim AS (SELECT *, [64, 64, 4, 8, 8, 1][benchmark + 1] AS cap FROM runs), pp AS (SELECT model, benchmark, problem_id, avg(CAST(correct AS INTEGER)) AS p, count(*) AS used FROM lim WHERE run_id <= cap GROUP BY ALL),
sc AS (SELECT model, benchmark, round(100 * avg(p), 6) AS score, count(*) AS problems, CAST(sum(used) AS BIGINT) AS runs FROM pp GROUP BY ALL)"""


@query("s01_avg_at_n", f"WITH {_AVG} SELECT * FROM sc")
def s01(spark, d):
    return ev.avg_at_n(ev.events_as_runs(table(spark, d, "events")))


@query("s02_macro_average", f"WITH {_AVG} SELECT model, round(avg(score), 6) AS average FROM sc GROUP BY model")
def s02(spark, d):
    return ev.macro_average(ev.avg_at_n(ev.events_as_runs(table(spark, d, "events"))))


@query("s03_gain", f"WITH {_AVG} SELECT a.model, a.benchmark, round(a.score - b.score, 6) AS points, round((a.score / b.score - 1) * 100, 6) AS relative FROM sc a JOIN sc b ON b.model = 'even' AND a.model <> 'even' AND a.benchmark = b.benchmark")
def s03(spark, d):
    return ev.gain(ev.avg_at_n(ev.events_as_runs(table(spark, d, "events"))), "even")


@query("w10_eval", f"WITH {_AVG} SELECT model, " + ", ".join(f"max(score) FILTER (WHERE benchmark = {b}) AS b{b}" for b in range(6)) + " FROM sc GROUP BY model")
def w10(spark, d):
    scores = ev.avg_at_n(ev.events_as_runs(table(spark, d, "events")))
    wide = scores.groupBy("model").pivot("benchmark", list(range(6))).agg(F.max("score"))
    return wide.select("model", *[F.col(str(b)).alias(f"b{b}") for b in range(6)])


@query("s04_data_share", "SELECT count(*) FILTER (WHERE lang = 'en') AS selected, count(*) AS pool, round(100.0 * count(*) FILTER (WHERE lang = 'en') / count(*), 6) AS share, round(100.0 * 92 / 800, 6) AS share_92k, round(100.0 * 165 / 800, 6) AS share_165k FROM documents")
def s04(spark, d):
    picked = F.count(F.when(F.col("lang") == "en", 1))
    return table(spark, d, "documents").agg(picked.alias("selected"), F.count(F.lit(1)).alias("pool"), F.round(100.0 * picked / F.count(F.lit(1)), 6).alias("share"), F.round(F.lit(100.0 * 92 / 800), 6).alias("share_92k"), F.round(F.lit(100.0 * 165 / 800), 6).alias("share_165k"))


def _box(source: str, groups: str) -> str:
    return f"""q AS (SELECT {groups}, quantile_cont(v, 0.25) AS q1, quantile_cont(v, 0.5) AS median, quantile_cont(v, 0.75) AS q3, min(v) AS low, max(v) AS high, count(*) AS n FROM {source} GROUP BY {groups})
SELECT {groups}, round(q1, 6) AS q1, round(median, 6) AS median, round(q3, 6) AS q3, low, high, n, min(v) FILTER (WHERE v BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1)) AS whisker_low,
max(v) FILTER (WHERE v BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1)) AS whisker_high, count(*) FILTER (WHERE NOT v BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1)) AS outliers
FROM {source} JOIN q USING ({groups}) GROUP BY {groups}, q1, median, q3, low, high, n"""


@query("s05_box_stats", f"WITH x AS (SELECT {o.DOMAIN} AS domain, n_chars AS v FROM documents), {_box('x', 'domain')}")
def s05(spark, d):
    docs = table(spark, d, "documents").select(domain_of_source(F.col("source")).alias("domain"), F.col("n_chars").alias("v"))
    return ev.box_stats(docs, ["domain"], "v").select("domain", *[F.round(c, 6).alias(c) for c in ("q1", "median", "q3")], "low", "high", "n", "whisker_low", "whisker_high", "outliers")


@query("s05_box_sketch", f"SELECT {o.DOMAIN} AS domain, quantile_disc(n_chars, 0.25) AS q1, quantile_disc(n_chars, 0.5) AS median, quantile_disc(n_chars, 0.75) AS q3, min(n_chars) AS low, max(n_chars) AS high, count(*) AS n FROM documents GROUP BY 1")
def s05_sketch(spark, d):
    docs = table(spark, d, "documents").select(domain_of_source(F.col("source")).alias("domain"), F.col("n_chars").alias("v"))
    return ev.box_stats_sketch(docs, ["domain"], "v")


@query("w07_length_levels", f"WITH {o.SCORED}, l AS (SELECT domain, n_chars AS v, ntile(4) OVER (ORDER BY complexity, doc_id) AS level FROM scored) SELECT domain, level, quantile_cont(v, 0.5) AS median, count(*) AS n FROM l GROUP BY ALL")
def w07(spark, d):
    from sparkcurate.operators.difficulty import difficulty_level
    from sparkcurate.plans.strategies import scored_documents

    scored = difficulty_level(scored_documents(table(spark, d, "documents")), "complexity", "doc_id")
    return scored.groupBy("domain", F.col("level").cast("long").alias("level")).agg(F.percentile("n_chars", F.lit(0.5)).alias("median"), F.count(F.lit(1)).alias("n"))


@query("w07_length_quality", "SELECT round(corr(n_chars, quality), 6) AS correlation, count(*) AS n FROM documents JOIN labels USING (doc_id)")
def w07_quality(spark, d):
    joined = table(spark, d, "documents").select("doc_id", "n_chars").join(table(spark, d, "labels"), "doc_id")
    return joined.agg(F.round(F.corr("n_chars", "quality"), 6).alias("correlation"), F.count(F.lit(1)).alias("n"))


_FAM = {k: " + ".join(f"len(regexp_extract_all(lower(text), '\\b{p}\\b'))" for p in v) for k, v in MARKERS.items()}


@query("s06_markers", "SELECT doc_id, " + ", ".join(f"{v} AS {k}" for k, v in _FAM.items()) + " FROM documents")
def s06(spark, d):
    return table(spark, d, "documents").select("doc_id", *[c.alias(k) for k, c in marker_counts(F.col("text"), MARKERS).items()])


@query("w06_markers", f"""WITH m AS (SELECT source, n_chars, {' + '.join(_FAM.values())} AS total FROM documents), s AS (SELECT source, avg(n_chars) AS chars, avg(total) AS markers, sum(total) * 1000.0 / sum(n_chars) AS per_1k FROM m GROUP BY source)
SELECT a.source, round(a.chars, 6) AS mean_chars, round(a.markers, 6) AS mean_markers, round(a.per_1k, 6) AS per_1k, round(a.chars / b.chars, 6) AS chars_ratio, round(a.markers / b.markers, 6) AS markers_ratio FROM s a JOIN s b ON b.source = 'src0'""")
def w06(spark, d):
    counts = marker_counts(F.col("text"), MARKERS)
    base = table(spark, d, "documents").select("source", "n_chars", sum(list(counts.values())[1:], list(counts.values())[0]).alias("total"))
    per = base.groupBy("source").agg(F.avg("n_chars").alias("chars"), F.avg("total").alias("markers"), (F.sum("total") * 1000.0 / F.sum("n_chars")).alias("per_1k"))
    first = per.filter("source = 'src0'").select(F.col("chars").alias("c0"), F.col("markers").alias("m0"))
    return per.crossJoin(F.broadcast(first)).select("source", F.round("chars", 6).alias("mean_chars"), F.round("markers", 6).alias("mean_markers"), F.round("per_1k", 6).alias("per_1k"), F.round(F.col("chars") / F.col("c0"), 6).alias("chars_ratio"), F.round(F.col("markers") / F.col("m0"), 6).alias("markers_ratio"))


@query("s07_stage_report", f"""WITH e AS (SELECT * FROM documents WHERE lang = 'en'), c AS (SELECT * FROM e WHERE len({o.tok('text')}) >= 5 AND regexp_matches(trim(text), '[.!?]$')), {o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)}
SELECT 'loaded' AS step, count(*) AS n FROM documents UNION ALL SELECT 'language', count(*) FROM e UNION ALL SELECT 'complete', count(*) FROM c UNION ALL SELECT 'clean', count(*) FROM c WHERE doc_id NOT IN (SELECT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg))""")
def s07(spark, d):
    docs = table(spark, d, "documents")
    english = filter_language(docs)
    complete = filter_complete(english)
    clean = complete.join(contaminated_any(complete, table(spark, d, "benchmark"), "doc_id"), "doc_id", "left_anti")
    out = None
    for name, rows in (("loaded", docs), ("language", english), ("complete", complete), ("clean", clean)):
        one = rows.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("step"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("s07_coverage", "WITH p AS (SELECT source, count(*) AS n FROM documents GROUP BY source) SELECT count(*) AS labels, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 6) AS entropy, max(n) - min(n) AS gap FROM p")
def s07_coverage(spark, d):
    return ev.coverage(table(spark, d, "documents"), "source")


_VAR = f"CASE WHEN len({o.tok('text')}) > 0 THEN round(len(list_distinct({o.tok('text')})) / len({o.tok('text')}), 6) ELSE 0.0 END"


@query("s08_filter_accuracy", f"""WITH x AS (SELECT {_VAR} >= 0.3 AS p, quality FROM documents JOIN labels USING (doc_id)), c AS (SELECT count(*) FILTER (WHERE p AND quality = 1) AS tp, count(*) FILTER (WHERE p AND quality = 0) AS fp, count(*) FILTER (WHERE NOT p AND quality = 1) AS fn, count(*) FILTER (WHERE NOT p AND quality = 0) AS tn FROM x)
SELECT tp, fp, fn, tn, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2.0 * tp / (2 * tp + fp + fn), 6) AS f1 FROM c""")
def s08(spark, d):
    joined = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select((heuristic_scores(F.col("text"))["variety"] >= 0.3).alias("p"), "quality")
    return ev.filter_accuracy(joined, "p", "quality")


@query("s08_auc", "WITH x AS (SELECT n_chars AS s, quality FROM documents JOIN labels USING (doc_id)), r AS (SELECT quality, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2.0 AS k FROM x) SELECT round((sum(k) FILTER (WHERE quality = 1) - count(*) FILTER (WHERE quality = 1) * (count(*) FILTER (WHERE quality = 1) + 1) / 2.0) / (count(*) FILTER (WHERE quality = 1) * count(*) FILTER (WHERE quality = 0)), 6) AS auc, count(*) FILTER (WHERE quality = 1) AS positives, count(*) FILTER (WHERE quality = 0) AS negatives FROM r")
def s08_auc(spark, d):
    joined = table(spark, d, "documents").select("doc_id", "n_chars").join(table(spark, d, "labels"), "doc_id")
    return ev.auc(joined, "n_chars", "quality")


@query("s09_work_counters", f"SELECT count(*) AS records, CAST(sum(len({o.tok('text')})) AS BIGINT) AS tokens, CAST(sum(greatest(len({o.tok('text')}) - 19, 0)) AS BIGINT) AS shingles FROM documents")
def s09(spark, d):
    words = n_tokens(F.col("text"))
    return table(spark, d, "documents").select(words.alias("t")).agg(F.count(F.lit(1)).alias("records"), F.sum("t").alias("tokens"), F.sum(F.greatest(F.col("t") - 19, F.lit(0))).alias("shingles"))


# Training settings that the reference reports for its two stages.
TRAINING = (("tuning", 5, 16, 1e-5, 8, None, None, None, None), ("preference", 3, 16, 5e-7, 16, "cosine", 0.1, 4, 0.1))
_SETTINGS = "stage string, epochs int, batch int, rate double, devices int, schedule string, warm_up double, sequence_parallel int, beta double"


def _value(x) -> str:
    return "NULL" if x is None else repr(x) if isinstance(x, str) else f"CAST({x} AS DOUBLE)" if isinstance(x, float) else str(x)


@query("s10_training_record", "WITH s AS (SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(_value, row)) + ")" for row in TRAINING) + """) AS t(stage, epochs, batch, rate, devices, schedule, warm_up, sequence_parallel, beta)),
r AS (SELECT 'tuning' AS stage, count(text) AS records, CAST(sum(length(text)) AS BIGINT) AS chars FROM documents UNION ALL SELECT 'preference', count(text), CAST(sum(length(text)) AS BIGINT) FROM conversations WHERE role = 'assistant')
SELECT s.*, records, chars, epochs * ((records + batch - 1) // batch) AS steps, epochs * chars AS chars_seen FROM s JOIN r USING (stage)""")
def s10(spark, d):
    return ev.training_record(
        spark.createDataFrame(list(TRAINING), _SETTINGS),
        {"tuning": table(spark, d, "documents").select("text"), "preference": table(spark, d, "conversations").filter("role = 'assistant'").select("text")},
    )


_TABLE = f"{_AVG}, p AS (SELECT model, CAST(sum(runs) AS BIGINT) AS data_size, {', '.join(f'max(score) FILTER (WHERE benchmark = {i}) AS {b}' for i, b in enumerate(ev.BENCHMARKS))}, round(avg(score), 2) AS printed FROM sc GROUP BY model)"
_MEAN = f"({' + '.join(ev.BENCHMARKS)}) / {len(ev.BENCHMARKS)}"


@query("w11_table_check", f"WITH {_TABLE} SELECT model, printed, round({_MEAN}, 4) AS recomputed, abs({_MEAN} - printed) < 0.0101 AS agrees FROM p")
def w11(spark, d):
    return ev.table_check(ev.baseline_table(ev.events_as_runs(table(spark, d, "events"))))


@query("b16_baselines", f"WITH {_TABLE} SELECT * FROM p")
def b16(spark, d):
    return ev.baseline_table(ev.events_as_runs(table(spark, d, "events")))


@query("w12_multi_turn", """WITH p AS (SELECT a.conv_id, a.turn, b.text AS response FROM conversations a LEFT JOIN conversations b ON b.conv_id = a.conv_id AND b.role = 'assistant' AND b.turn = (SELECT min(c.turn) FROM conversations c WHERE c.conv_id = a.conv_id AND c.turn > a.turn) WHERE a.role = 'user')
SELECT count(*) AS pairs, count(DISTINCT conv_id) AS conversations, count(*) FILTER (WHERE response IS NULL) AS missing, count(*) FILTER (WHERE regexp_matches(trim(response), '[.!?]$')) AS closed FROM p""")
def w12(spark, d):
    from sparkcurate.sources.tables import to_qa_pairs

    pairs = to_qa_pairs(table(spark, d, "conversations"))
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.countDistinct("conv_id").alias("conversations"), F.count(F.when(F.col("response").isNull(), 1)).alias("missing"), F.count(F.when(F.trim("response").rlike(r"[.!?]$"), 1)).alias("closed"))
