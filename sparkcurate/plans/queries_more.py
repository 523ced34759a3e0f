"""Clients, verifiers, budgets by share, work counters, sketches, samples, sinks, and the pipeline that SQL can repeat."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import ship_package
from sparkcurate.functions.lineage import shared_folder
from sparkcurate.functions.text import grams, seeded
from sparkcurate.operators import difficulty as di
from sparkcurate.operators import evaluate as ev
from sparkcurate.operators import quality as qu
from sparkcurate.operators import relational as rl
from sparkcurate.operators import rules as ru
from sparkcurate.operators import select as se
from sparkcurate.operators.cluster import cluster, encode_md5
from sparkcurate.operators.decontam import contaminated_any, max_cosine
from sparkcurate.operators.dedup import overlap_pairs
from sparkcurate.operators.semantic import combine_rejections
from sparkcurate.plans import oracle_text as o
from sparkcurate.plans.pipeline import Config, encode_sums, run_pipeline
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import read_files, table, write_bucketed, write_files

_WORDS = {"math": ["the", "of", "der"], "code": ["license", "version", "les"], "science": ["und", "los", "et"]}
_HITS = {k: f"len(list_filter({o.tok('text')}, lambda w: w IN ({', '.join(repr(w) for w in v)})))" for k, v in _WORDS.items()}


@query("m07_lexicon", f"""WITH h AS (SELECT doc_id, {', '.join(f'{v} AS {k}' for k, v in _HITS.items())} FROM documents)
SELECT doc_id, CASE greatest(math, code, science) WHEN 0 THEN 'other' WHEN math THEN 'math' WHEN code THEN 'code' ELSE 'science' END AS domain FROM h""")
def m07_lexicon(spark, d):
    return ru.annotate_domain(table(spark, d, "documents"), "lexicon", "text", _WORDS, "other").select("doc_id", "domain")


_LABELS = ["math/algebra", "math/geometry", "code/python", "science"]


@query("m07_client", f"""WITH l AS (SELECT doc_id, [{', '.join(repr(x) for x in _LABELS)}][CAST('0x' || substr(md5(doc_id || ':1'), 1, 2) AS INTEGER) % 4 + 1] AS label FROM documents)
SELECT doc_id, split_part(label, '/', 1) AS domain, CASE WHEN strpos(label, '/') > 0 THEN split_part(label, '/', 2) ELSE label END AS category FROM l""")
def m07_client(spark, d):
    return qu.annotate_with(table(spark, d, "documents"), qu.StubLabels(_LABELS), _LABELS, "doc_id", "text")


@query("m16_verify_program", """WITH r AS (SELECT doc_id, CASE doc_id % 4 WHEN 0 THEN NULL WHEN 1 THEN doc_id WHEN 2 THEN doc_id + 1 ELSE doc_id END AS last FROM documents)
SELECT doc_id, coalesce(last = doc_id, false) AS passed FROM r""")
def m16_program(spark, d):
    # no program, a right one, a wrong one behind a right one, a right one behind a wrong one
    block = lambda n: F.concat(F.lit("```python\nprint("), n.cast("string"), F.lit(")\n```\n"))
    key, text = F.col("doc_id"), F.coalesce(F.col("text"), F.lit(""))
    response = F.when(key % 4 == 0, F.replace(text, F.lit("`"), F.lit(""))).when(key % 4 == 1, block(key)).when(key % 4 == 2, F.concat(block(key), block(key + 1))).otherwise(F.concat(block(key + 1), block(key)))
    return qu.verify(table(spark, d, "documents").select("doc_id", response.alias("response"), key.cast("string").alias("truth")), qu.ProgramVerifier(qu.StubSandbox())).select("doc_id", "passed")


_RATED = "SELECT doc_id, " + ", ".join(f"CAST('0x' || substr(md5(doc_id || ':{a}'), 1, 2) AS INTEGER) / 255 AS {a}" for a in qu.ASPECTS) + " FROM documents"


@query("m18_judge_client", f"SELECT doc_id, {', '.join(f'round({a}, 6) AS {a}' for a in qu.ASPECTS)} FROM ({_RATED}) WHERE clarity >= 0.3 AND informativeness >= 0.3 AND redundancy <= 0.7 AND confidence >= 0.5")
def m18_client(spark, d):
    judged = qu.judge(table(spark, d, "documents"), qu.StubJudge(), "doc_id", "text")
    return qu.filter_by_judge(judged).select("doc_id", *[F.round(a, 6).alias(a) for a in qu.ASPECTS])


def _vectors(name: str, key: str, size: int) -> str:
    return o.vectors(name, key, size)


_COS = f"""{_vectors('documents', 'doc_id', 64)}, {_vectors('benchmark', 'item_id', 64)},
c AS (SELECT a.doc_id, max(CASE WHEN a.n > 0 AND b.n > 0 THEN list_sum(list_transform(list_zip(a.v, b.v), lambda p: p[1] * p[2])) / (sqrt(a.n) * sqrt(b.n)) ELSE 0 END) AS cosine FROM vec_documents a, vec_benchmark b GROUP BY a.doc_id)"""


@query("m21_benchmark_cosine", f"WITH {_COS} SELECT doc_id, round(cosine, 6) AS cosine FROM c")
def m21_benchmark(spark, d):
    """Whole documents against the encoded benchmark items."""
    found = max_cosine(encode_sums(table(spark, d, "documents"), "doc_id", "text"), encode_sums(table(spark, d, "benchmark"), "item_id", "text"), "doc_id")
    return found.select("doc_id", F.round("cosine", 6).alias("cosine"))


_LEX = f"{o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)}, hit AS (SELECT DISTINCT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg))"


@query("m22_combined_benchmark", f"WITH {_COS}, {_LEX}, j AS (SELECT doc_id, cosine > 0.6 AS semantic, doc_id IN (SELECT doc_id FROM hit) AS lexical FROM c) SELECT * FROM j WHERE semantic OR lexical")
def m22_benchmark(spark, d):
    """Both rules of the same documents and items; the mark is lower than the default, for whole documents only hold the items."""
    docs, benchmark = table(spark, d, "documents"), table(spark, d, "benchmark")
    semantic = max_cosine(encode_sums(docs, "doc_id", "text"), encode_sums(benchmark, "item_id", "text"), "doc_id").filter("cosine > 0.6").select("doc_id")
    return combine_rejections(contaminated_any(docs, benchmark, "doc_id"), semantic, "doc_id")


@query("m09_encode_sums", f"WITH {_vectors('documents', 'doc_id', 64)} SELECT doc_id, CAST(n AS BIGINT) AS square, CAST(v[1] AS BIGINT) AS first, CAST(v[64] AS BIGINT) AS last FROM vec_documents")
def m09_sums(spark, d):
    coded = encode_md5(table(spark, d, "documents"), "doc_id", "text", 64)
    return coded.select("doc_id", F.aggregate("v", F.lit(0).cast("long"), lambda s, x: s + x * x).alias("square"), F.get("v", F.lit(0)).alias("first"), F.get("v", F.lit(63)).alias("last"))


@query("m10_mixture")
def m10_mixture(spark, d):
    found, _ = cluster(table(spark, d, "embeddings").withColumn("embedding", F.slice("embedding", 1, 8)), "vec_id", 4, algo="mixture")
    return found.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


_ELIGIBLE = f"e AS (SELECT doc_id, source AS category, {o.RND} AS rnd FROM documents WHERE lang = 'en' AND len({o.tok('text')}) >= 5 AND regexp_matches(trim(text), '[.!?]$')), r AS (SELECT doc_id, category, row_number() OVER (PARTITION BY category ORDER BY rnd, doc_id) AS rn FROM e), k AS (SELECT doc_id, row_number() OVER (ORDER BY rn, category) AS place FROM r)"


@query("w01_budgets", f"WITH {_ELIGIBLE} SELECT doc_id, place <= CAST(round_even(0.08 * (SELECT count(*) FROM e), 0) AS BIGINT) AS small FROM k WHERE place <= CAST(round_even(0.15 * (SELECT count(*) FROM e), 0) AS BIGINT)")
def w01_budgets(spark, d):
    """Both published budgets as shares of the eligible records, balanced over categories; the small one lies in the large one."""
    docs = ru.filter_complete(ru.filter_language(table(spark, d, "documents"))).select("doc_id", F.col("source").alias("category")).withColumn("rnd", seeded("doc_id"))
    total, order = docs.count(), [F.col("rnd"), F.col("doc_id")]
    small = se.sample_balanced(docs, "category", round(0.08 * total), order).select("doc_id", F.lit(True).alias("small"))
    return se.sample_balanced(docs, "category", round(0.15 * total), order).join(small, "doc_id", "left").select("doc_id", F.coalesce("small", F.lit(False)).alias("small"))


@query("s09_attempts", """WITH t AS (SELECT doc_id, a FROM documents, (SELECT unnest(generate_series(1, 8)) AS a) WHERE CAST('0x' || substr(md5(doc_id || ':' || a), 1, 1) AS INTEGER) < 5),
r AS (SELECT doc_id, CAST(coalesce(min(a), 8) AS INTEGER) AS attempts, min(a) IS NOT NULL AS passed FROM documents LEFT JOIN t USING (doc_id) GROUP BY doc_id)
SELECT attempts, passed, records, (attempts - 1) * records AS calls FROM (SELECT attempts, passed, count(*) AS records FROM r GROUP BY attempts, passed)""")
def s09_attempts(spark, d):
    return ev.attempt_histogram(qu.verify_regenerate_stub(table(spark, d, "documents"), "doc_id"))


@query("s09_pair_work", f"""WITH {o.grams('g', 'documents', 'doc_id', 20)}, s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id), m AS (SELECT gram, count(*) AS n FROM g GROUP BY gram),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL)
SELECT (SELECT CAST(sum(n) AS BIGINT) FROM m) AS shingles, (SELECT count(*) FROM m) AS distinct_shingles, (SELECT CAST(sum(n * (n - 1) // 2) AS BIGINT) FROM m) AS meetings,
(SELECT count(*) FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8) AS pairs""")
def s09_pairs(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "text")
    return ev.pair_work(grams(docs, "doc_id", "text", 20), overlap_pairs(docs, "doc_id", "text"))


@query("s09_step_work", "SELECT count(*) AS rows, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes FROM documents WHERE lang = 'en'")
def s09_step(spark, d):
    return ev.step_work(ru.filter_language(table(spark, d, "documents")), "text")


@query("b15_scorers", f"SELECT doc_id, len({o.tok('text')}) AS length, round(CASE WHEN len({o.tok('text')}) > 0 THEN len(list_distinct({o.tok('text')})) / len({o.tok('text')}) ELSE 0.0 END, 6) AS variety FROM documents")
def b15_scorers(spark, d):
    return di.score_with(table(spark, d, "documents"), "doc_id", "text", ("length", "variety")).select("doc_id", "length", F.round("variety", 6).alias("variety"))


@query("op_sketches", """SELECT event_type, count(DISTINCT user_id) AS users, true AS hll_near, true AS theta_near, true AS median_near FROM events GROUP BY event_type""")
def sketches(spark, d):
    """Mergeable sketches by day, merged by type, against the exact answers."""
    events = table(spark, d, "events").withColumn("day", F.to_date("ts"))
    daily = events.groupBy("event_type", "day").agg(F.hll_sketch_agg("user_id", F.lit(14)).alias("hll"), F.theta_sketch_agg("user_id").alias("theta"))
    merged = daily.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("hll")).alias("hll"), F.theta_sketch_estimate(F.theta_union_agg("theta")).alias("theta"))
    exact = events.groupBy("event_type").agg(
        F.countDistinct("user_id").alias("users"), F.percentile_approx("value", 0.5, 200).alias("near"), F.percentile("value", F.lit(0.47)).alias("low"), F.percentile("value", F.lit(0.53)).alias("high"),
    )
    near = lambda c: F.abs(F.col(c) - F.col("users")) <= 0.05 * F.col("users") + 1
    return exact.join(merged, "event_type").select("event_type", "users", near("hll").alias("hll_near"), near("theta").alias("theta_near"), F.col("near").between(F.col("low"), F.col("high")).alias("median_near"))


@query("op_reservoir", f"SELECT source, doc_id FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY {o.RND}, doc_id) AS k FROM documents) WHERE k <= 7")
def reservoir(spark, d):
    docs = table(spark, d, "documents").select("source", "doc_id").withColumn("rnd", seeded("doc_id"))
    return se.top_per_group(docs, ["source"], [F.col("rnd"), F.col("doc_id")], 7).select("source", "doc_id")


@query("op_sample_by", "SELECT lang, true AS near FROM documents WHERE lang IN ('en', 'fr') GROUP BY lang")
def sample_by(spark, d):
    """A stratified Bernoulli sample lies within five deviations of its fractions."""
    docs = table(spark, d, "documents").filter("lang IN ('en', 'fr')").select("lang", "doc_id")
    some = docs.sampleBy("lang", {"en": 0.2, "fr": 0.6}, seed=42).groupBy("lang").agg(F.count(F.lit(1)).alias("k"))
    share = F.when(F.col("lang") == "en", 0.2).otherwise(0.6)
    return docs.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).join(some, "lang", "left").select("lang", (F.abs(F.coalesce("k", F.lit(0)) - share * F.col("n")) <= 5 * F.sqrt(F.col("n") * share * (1 - share))).alias("near"))


@query("op_cogroup", """WITH b AS (SELECT user_id, ts, value FROM events WHERE event_type = 'click'), p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase')
SELECT p.event_id, (SELECT count(*) FROM b WHERE b.user_id = p.user_id AND b.ts <= p.ts) AS clicks FROM p""")
def cogroup(spark, d):
    """Clicks before each purchase: the two tables of a user meet in one call."""
    ship_package(spark)

    def clicks(purchases: pd.DataFrame, clicked: pd.DataFrame) -> pd.DataFrame:
        times = clicked["ts"].sort_values()
        return pd.DataFrame({"event_id": purchases["event_id"], "clicks": times.searchsorted(purchases["ts"], side="right")})

    events = table(spark, d, "events")
    return events.filter("event_type = 'purchase'").groupBy("user_id").cogroup(events.filter("event_type = 'click'").groupBy("user_id")).applyInPandas(clicks, "event_id long, clicks long")


@query("op_variant", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def variant(spark, d):
    return table(spark, d, "events").select(F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("op_sinks", """SELECT f.format, count(*) AS n, CAST(sum(doc_id) AS BIGINT) AS ids FROM documents, (SELECT unnest(['parquet', 'json', 'csv', 'orc', 'bucketed']) AS format) f WHERE lang IS NOT NULL GROUP BY 1""")
def sinks(spark, d):
    """Every sink written and read again by its source, partitioned by language, or in buckets."""
    docs = table(spark, d, "documents").filter("lang IS NOT NULL").select("doc_id", "n_chars", "lang")
    folder, out = f"{shared_folder(spark)}/sinks-{uuid.uuid4().hex}", None
    for form in ("parquet", "json", "csv", "orc"):
        write_files(docs, f"{folder}/{form}", form, ("lang",))
        one = read_files(spark, f"{folder}/{form}", form, "doc_id long, n_chars long, lang string")
        one = one.select(F.lit(form).alias("format"), "doc_id")
        out = one if out is None else out.unionByName(one)
    out = out.unionByName(write_bucketed(docs, f"{folder}/bucketed", "doc_id", 8).select(F.lit("bucketed").alias("format"), "doc_id"))
    return out.groupBy("format").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("ids"))


@query("op_level_ranks", "SELECT source, ntile(3) OVER (PARTITION BY source ORDER BY n_chars, doc_id) AS level, doc_id FROM documents")
def level_ranks(spark, d):
    """Levels inside groups without a window over a group."""
    return di.difficulty_level(table(spark, d, "documents").select("doc_id", "source", "n_chars"), "n_chars", "doc_id", 3, "source").select("source", F.col("level").cast("long").alias("level"), "doc_id")


@query("op_theta_join", "SELECT e.event_id, count(*) AS longer FROM events e JOIN orders o ON o.o_totalprice > 400000 AND o.o_orderdate < e.ts WHERE e.event_type = 'purchase' GROUP BY e.event_id")
def theta(spark, d):
    """An inequality join as a running count: one sorted union instead of pairs."""
    events = table(spark, d, "events").filter("event_type = 'purchase'").select("event_id", F.col("ts").alias("t"))
    orders = table(spark, d, "orders").filter("o_totalprice > 400000").select(F.col("o_orderdate").alias("t"))
    return rl.count_before(events, orders, "t", "longer").filter("longer > 0").select("event_id", "longer")


_W01 = f"""pool AS (SELECT * FROM documents WHERE lang = 'en' AND len({o.tok('text')}) >= 5 AND regexp_matches(trim(text), '[.!?]$')),
{o.SCORED.replace('FROM documents', 'FROM pool')}, bud AS (SELECT CAST(round_even(0.15 * count(*), 0) AS BIGINT) AS b FROM pool),
pick AS (SELECT doc_id FROM {o.dual('scored', 'n_chars DESC, doc_id', '(SELECT b FROM bud)')}), picked AS (SELECT * FROM pool WHERE doc_id IN (SELECT doc_id FROM pick)),
{o.vectors('picked', 'doc_id', 64)}, {o.vectors('benchmark', 'item_id', 64)},
near_item AS (SELECT DISTINCT a.doc_id FROM vec_picked a, vec_benchmark b WHERE a.n > 0 AND b.n > 0 AND list_sum(list_transform(list_zip(a.v, b.v), lambda p: p[1] * p[2])) / (sqrt(a.n) * sqrt(b.n)) > 0.9),
{o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'picked', 'doc_id', 15)},
clean AS (SELECT * FROM picked WHERE doc_id NOT IN (SELECT doc_id FROM near_item) AND doc_id NOT IN (SELECT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg))),
{o.grams('g', 'clean', 'doc_id', 20)}, sz AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
pr AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL),
free AS (SELECT *, {o.DOMAIN} AS domain FROM clean WHERE doc_id NOT IN (SELECT b FROM pr JOIN sz sa ON sa.doc_id = a JOIN sz sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8)),
formed AS (SELECT * FROM free WHERE trim(text) <> '' AND regexp_matches(text, '[.!?}}`]\\s*$') AND len({o.tok('text')}) <= 32768),
tries AS (SELECT doc_id FROM formed, (SELECT unnest(generate_series(1, 8)) AS a) WHERE CAST('0x' || substr(md5(doc_id || ':' || a), 1, 1) AS INTEGER) < 5),
heur AS (SELECT *, {o.tok('text')} AS t, string_split(text, chr(10)) AS l FROM formed WHERE domain = 'science'),
good AS (SELECT doc_id, domain, source AS category, n_chars FROM formed WHERE domain <> 'science' AND doc_id IN (SELECT doc_id FROM tries)
  UNION ALL SELECT doc_id, domain, source, n_chars FROM heur WHERE round(len(list_distinct(t)) / len(t), 6) >= 0.3 AND round(1 - len(list_distinct(l)) / len(l), 6) <= 0.3 AND round(length(regexp_replace(text, '[\\p{{L}}\\p{{N}}\\s]', '', 'g')) / length(text), 6) <= 0.15),
held AS (SELECT domain, count(*) AS n, CASE domain WHEN 'science' THEN 3 ELSE 4 END AS w FROM good GROUP BY domain),
most AS (SELECT min(n * (SELECT sum(w) FROM held) // w) AS b FROM held),
mixed AS (SELECT doc_id, domain, category, n_chars FROM (SELECT *, (2 * row_number() OVER (PARTITION BY domain ORDER BY n_chars DESC, doc_id) - 1) * CASE domain WHEN 'science' THEN 4 ELSE 3 END AS k FROM good) QUALIFY row_number() OVER (ORDER BY k, domain) <= (SELECT b FROM most)),
final AS (SELECT *, CASE WHEN row_number() OVER (ORDER BY CASE WHEN domain IN ('math', 'code') THEN 0 ELSE 1 END, n_chars, doc_id) <= floor((SELECT count(*) FROM mixed) * 0.7 + 1e-9) THEN 1 ELSE 2 END AS stage FROM mixed)"""


@query("w01_pipeline_given", f"WITH {_W01} SELECT * FROM final")
def w01_given(spark, d):
    """The whole pipeline with clusters and vectors that SQL can repeat."""
    return run_pipeline(spark, d, Config(fitted=False))[0].select("doc_id", "domain", "category", "n_chars", "stage")


_STEPS = {"loaded": "documents", "rules": "pool", "sampled": "pick", "overlap": "free", "format": "formed", "verified": "good", "mixed": "mixed"}


@query("w01_pipeline_given_report", f"WITH {_W01} " + " UNION ALL ".join(f"SELECT '{k}' AS step, count(*) AS rows FROM {v}" for k, v in _STEPS.items()))
def w01_given_report(spark, d):
    return run_pipeline(spark, d, Config(fitted=False))[1]
