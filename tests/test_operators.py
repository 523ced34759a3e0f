"""Operators against brute force, and their defined cases."""

import collections
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparkcurate.functions.text import gram_hashes, tokens
from sparkcurate.operators.cluster import assign, assign_batched, cluster, cluster_hierarchical, encode, lloyd_step, register_algorithm
from sparkcurate.operators.decontam import contaminated_share, decontaminate_ngrams, max_cosine
from sparkcurate.operators.dedup import drop_by_pairs, drop_contained, overlap_pairs, shares_any
from sparkcurate.operators.difficulty import difficulty_level, difficulty_level_by_cuts, score_compression
from sparkcurate.operators.evaluate import auc, box_stats, box_stats_sketch, step_work
from sparkcurate.operators.judge import quality_scores
from sparkcurate.operators.mix import mix, ratio_budget
from sparkcurate.operators.quality import ProgramVerifier, StubClient, StubSandbox, last_program, verify, verify_regenerate
from sparkcurate.operators.relational import as_of, count_before, range_join, salted_join
from sparkcurate.operators.rules import annotate_domain, format_reasons
from sparkcurate.operators.select import running_sum, sample_balanced, sample_nested
from sparkcurate.operators.semantic import chunked_contamination, strict_pool
from sparkcurate.plans.pipeline import distilled, ingest
from sparkcurate.plans.queries_stream import decontaminate
from sparkcurate.streaming import stream as st


def grams_of(text, n):
    import re

    w = [x for x in re.split(r"[\W_]+", (text or "").lower()) if x]
    return [tuple(w[i : i + n]) for i in range(len(w) - n + 1)]


@pytest.mark.parametrize("n", [1, 2, 3, 7, 15, 20])
def test_gram_hashes_tell_grams_apart(spark, n):
    texts = ["", "a", "a b c d e f g h i j k l m n o p q r s t u v", "a b " * 30, "x " * 41, "a b c d e f g h i j k l m n o p q r s T U w"]
    docs = spark.createDataFrame([(t,) for t in [*texts, None]], "text string")
    got = [r[0] for r in docs.select(gram_hashes(tokens(F.col("text")), n)).collect()]
    flat = [(h, g) for hashes, t in zip(got, [*texts, None], strict=True) for h, g in zip(hashes, grams_of(t, n), strict=True)]
    assert len({h for h, _ in flat}) == len({g for _, g in flat}) == len(set(flat))


def test_drop_contained_equals_all_pairs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").unionByName(spark.createDataFrame([(9001, "short one"), (9002, "short one"), (9003, None), (9004, None)], "doc_id long, text string"))
    docs = docs.withColumn("rank", F.length("text") % 5)
    pairs = overlap_pairs(docs, "doc_id", "text")
    for priority in (None, "rank"):
        expected = {r.doc_id for r in drop_by_pairs(docs, "doc_id", pairs, priority).collect()}
        assert {r.doc_id for r in drop_contained(docs, "doc_id", "text", priority=priority).collect()} == expected
    assert drop_contained(docs.limit(0), "doc_id", "text").count() == shares_any(docs.limit(0), "doc_id", "text").count() == 0


def test_null_labels_are_a_group(spark):
    rows = spark.createDataFrame([(i, None if i % 3 == 0 else "ab"[i % 2], "x" if i % 4 else None) for i in range(60)], "doc_id long, g string, h string")
    assert collections.Counter(r.g for r in sample_balanced(rows, "g", 30, [F.col("doc_id")]).collect()) == {None: 10, "a": 10, "b": 10}
    assert sample_nested(rows, "g", "h", 24, [F.col("doc_id")]).count() == 24
    assert sample_balanced(rows, "g", 0, [F.col("doc_id")]).count() == sample_balanced(rows.limit(0), "g", 5, [F.col("doc_id")]).count() == 0
    assert sample_balanced(rows, "g", 999, [F.col("doc_id")]).count() == 60


def test_running_sums_and_levels(spark):
    rows = spark.createDataFrame([(i, (i * 37) % 11, i % 3) for i in range(103)], "id long, s long, g long").repartition(7)
    order = sorted(((i * 37) % 11, i) for i in range(103))
    got = {r.id: r.before for r in running_sum(rows, ["s", "id"], F.col("id"), "before").collect()}
    assert all(got[i] == sum(x for _, x in order[:k]) for k, (_, i) in enumerate(order))
    for levels in (4, 7, 200):
        assert {(r.id, r.level) for r in difficulty_level(rows, "s", "id", levels).collect()} == {(r.id, r.level) for r in rows.selectExpr("id", f"ntile({levels}) over (order by s, id) level").collect()}


def test_auc_equals_pairs(spark):
    rows = [(x % 7 / 3, int(x * 13 % 5 < 2)) for x in range(60)]
    good, bad = [s for s, t in rows if t], [s for s, t in rows if not t]
    wins = sum((a > b) + 0.5 * (a == b) for a in good for b in bad)
    assert auc(spark.createDataFrame(rows, "s double, t int"), "s", "t").first().auc == pytest.approx(wins / len(good) / len(bad), abs=1e-6)
    assert auc(spark.createDataFrame([(1.0, 1)], "s double, t int"), "s", "t").first().auc is None


def test_box_stats(spark):
    values = [1, 2, 2, 3, 4, 5, 100]
    r = box_stats(spark.createDataFrame([("a", v) for v in values], "g string, v long"), ["g"], "v").first()
    assert (r.q1, r.median, r.q3, r.whisker_low, r.whisker_high, r.outliers) == (*np.percentile(values, [25, 50, 75]), 1, 5, 1)


def test_levels_by_cuts_are_exact(spark):
    rows = [(i, i * i % 9973, "ab"[i % 7 // 6]) for i in range(3000)] + [(3000, None, "a"), (3001, 5, None), (3002, None, "c")]
    frame = spark.createDataFrame(rows, "id long, s long, g string").repartition(5)
    for by in (None, "g"):
        got = {r.id: r.level for r in difficulty_level_by_cuts(frame, "s", 5, by, accuracy=4).collect()}
        for name in {g for *_, g in rows} if by else [None]:
            some = [(i, v) for i, v, g in rows if not by or g == name]
            held = sorted(v for _, v in some if v is not None)
            cuts = [held[max(len(held) - (len(held) * (5 - k)) // 5, 1) - 1] for k in range(1, 5)] if held else None
            assert all(got[i] == (None if cuts is None else 1 + sum(v is not None and c < v for c in cuts)) for i, v in some)
    assert difficulty_level_by_cuts(frame.limit(0), "s").count() == 0


def test_box_sketch_is_exact(spark):
    rows = [("ab"[i % 7 // 6], i * i % 9973) for i in range(3000)] + [(None, 7), ("a", None), ("c", None)]
    got = {r.g: tuple(r)[1:] for r in box_stats_sketch(spark.createDataFrame(rows, "g string, v long").repartition(5), ["g"], "v", 4).collect()}
    for name in {g for g, _ in rows}:
        held = sorted(v for g, v in rows if g == name and v is not None)
        quart = [held[max(-(-len(held) * k // 4), 1) - 1] for k in (1, 2, 3)] if held else [None] * 3
        assert got[name] == (*quart, min(held, default=None), max(held, default=None), sum(g == name for g, _ in rows))


def test_clustering(spark, sf):
    vectors = spark.read.parquet(f"{sf}/embeddings.parquet").limit(200)
    register_algorithm("first", lambda v, k, seed: [r["features"].toArray() for r in v.limit(k).collect()])
    costs = {}
    for algo in ("first", "kmeans", "bisecting"):
        told, centres = cluster(vectors, "vec_id", 5, algo=algo)
        costs[algo] = told.agg(F.sum("dist")).first()[0]
        x = {r.vec_id: np.array(r.embedding, float) for r in vectors.collect()}
        c = {r.cluster: np.array(r.center) for r in centres.collect()}
        assert all(r.dist == pytest.approx(min(((x[r.vec_id] - v) ** 2).sum() for v in c.values()), abs=1e-9) for r in told.collect())
    assert costs["kmeans"] < costs["first"]
    assert {(r.vec_id, r.cluster) for r in assign(vectors, centres, "vec_id").collect()} == {(r.vec_id, r.cluster) for r in assign_batched(vectors, centres, "vec_id").collect()}
    moved = lloyd_step(vectors, told, "vec_id").groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "value"))), lambda p: p["value"]).alias("center"))
    assert assign_batched(vectors, moved, "vec_id").agg(F.sum("dist")).first()[0] <= costs["bisecting"] + 1e-9
    fine = cluster_hierarchical(vectors, "vec_id", 3, 4)
    assert fine.count() == 200 and 3 < fine.select("cluster").distinct().count() <= 12


def test_encode_equals_brute_force(spark):
    import zlib

    texts = ["One two three, four!", "one TWO three four", "a b", "", None]
    got = [np.array(r.embedding) for r in encode(spark.createDataFrame(list(enumerate(texts)), "id long, t string"), "id", "t", 32).orderBy("id").collect()]
    x = np.zeros(32)
    for g in ("one two three", "two three four"):
        h = zlib.crc32(g.encode(), 42)
        x[h % 32] += 1 if (h >> 20) & 1 else -1
    assert np.allclose(got[0], x / np.linalg.norm(x), atol=1e-6) and np.allclose(got[0], got[1]) and np.linalg.norm(got[2]) == pytest.approx(1) and not got[3].any() and not got[4].any()


def test_chunked_cosine_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    word = lambda k: [f"w{x}" for x in rng.integers(0, 40, k)]
    items = [word(12), word(30), ["r"] * 9, word(2)]
    docs = [word(80), [*word(10), *items[0], *word(9)], [*items[1][:24], *word(4), *items[1][24:]], ["r"] * 30, [*items[1][:28], "z"], [], items[0][:11]]
    frame = lambda rows, key: spark.createDataFrame([(i, " ".join(r)) for i, r in enumerate(rows)], f"{key} long, text string")
    expected = {}
    for i, a in enumerate(docs):
        for j, b in enumerate(items):
            x, y = ([tuple(t[k : k + 3]) for k in range(len(t) - 2)] for t in (a, b))
            for s in range(max(0, len(x) - min(len(x), len(y)) + 1) if x and y else 0):
                p, q = collections.Counter(x[s : s + min(len(x), len(y))]), collections.Counter(y)
                cosine = sum(p[g] * q[g] for g in p) / math.sqrt(sum(v * v for v in p.values()) * sum(v * v for v in q.values()))
                if cosine > 0.9:
                    expected[i, j] = max(expected.get((i, j), 0), cosine)
    got = {(r.doc_id, r.item_id): r.cosine for r in chunked_contamination(frame(docs, "doc_id"), frame(items, "item_id")).collect()}
    assert got == pytest.approx(expected) and len(got) >= 3


def test_strict_pool_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    vectors = {r.doc_id: np.array(r.embedding) for r in encode(docs, "doc_id", "text", d=256).collect()}
    sets = {r.doc_id: set(grams_of(r.text, 15)) for r in docs.collect()}
    ids = sorted(sets)
    matrix = np.array([vectors[i] for i in ids])
    close = matrix @ matrix.T > 0.9
    gone = {b for y, b in enumerate(ids) for x, a in enumerate(ids[:y]) if close[x, y] or (sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * min(len(sets[a]), len(sets[b])))}
    assert {r.doc_id for r in strict_pool(docs).collect()} == set(ids) - gone


def test_max_cosine_cases(spark):
    vectors = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 0.0]), (3, [0.9, math.sqrt(1 - 0.81)])], "id long, embedding array<double>")
    items = spark.createDataFrame([([2.0, 0.0],)], "embedding array<double>")
    got = {r.id: r.cosine for r in max_cosine(vectors, items, "id").collect()}
    # a cosine of the threshold itself does not reject
    assert got[1] == 1 and got[2] == 0 and got[3] == pytest.approx(0.9)
    assert {r.cosine for r in max_cosine(vectors, items.limit(0), "id").collect()} == {-1.0}


def test_cosines_of_whole_numbers_are_those_of_sql(spark):
    dice = np.random.default_rng(1)
    a, b = dice.integers(-9, 10, (200, 16)), dice.integers(-9, 10, (20, 16))
    frame = lambda v: spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "id long, embedding array<double>")
    got = {r.id: r.cosine for r in max_cosine(frame(a), frame(b), "id").collect()}
    # to the last bit: a cosine of 0.6 itself must not pass for more
    assert got == {i: max(int(v @ w) / (math.sqrt(v @ v) * math.sqrt(w @ w)) for w in b) for i, v in enumerate(a)}


def test_overlap_of_exactly_n_words(spark):
    item = " ".join(f"w{i}" for i in range(30))
    docs = spark.createDataFrame([(k, "Zz " + ", ".join(f"W{i}" for i in range(k)) + " yy") for k in (14, 15, 16)] + [(1, None), (2, "")], "doc_id long, text string")
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert sorted(r.doc_id for r in decontaminate_ngrams(docs, bench, "doc_id").collect()) == [1, 2, 14]
    assert {r.doc_id: round(r.share * 16) for r in contaminated_share(docs, bench, "doc_id").collect()} == {15: 1, 16: 2}
    assert decontaminate_ngrams(docs, bench.limit(0), "doc_id").count() == 5


def test_joins_equal_brute_force(spark):
    left = [(i, i % 3, i * 7 % 50) for i in range(40)] + [(98, None, 5), (99, 1, None)]
    right = [(i % 3, i * 11 % 50, i) for i in range(20)]
    a, b = spark.createDataFrame(left, "id long, k long, t long"), spark.createDataFrame(right, "k long, t long, v long")
    got = {r.id: r.last_v for r in as_of(a, b, "k", "t", "v").collect()}
    for i, k, t in left:
        before = [(u, v) for j, u, v in right if t is not None and j == k and u <= t]
        assert i in (98, 99) or got[i] in ([v for u, v in before if u == max(before)[0]] if before else [None])
    spans = spark.createDataFrame([(i, i * 3, i * 3 + 10) for i in range(10)], "r long, lo long, hi long")
    held = {(x.id, x.r) for x in range_join(a.filter("t is not null"), spans, "t", "lo", "hi", 4).collect()}
    assert held == {(i, r) for i, _, t in left if t is not None for r in range(10) if r * 3 <= t < r * 3 + 10}
    assert salted_join(a, b.withColumnRenamed("t", "u"), "k").count() == sum(1 for _, k, _ in left for j, _, _ in right if j == k)
    assert {r.id: r.n for r in count_before(a, b.select("t"), "t", "n").collect()} == {i: sum(u < t for _, u, _ in right) for i, _, t in left if t is not None}


def test_salted_join_never_broadcasts_the_repeated_side(spark):
    joined = salted_join(spark.range(1000).selectExpr("id % 7 AS k", "id"), spark.range(7).selectExpr("id AS k", "id AS v"), "k")
    assert joined.count() == 1000 and joined.filter("k <> v").count() == 0
    assert "Broadcast" not in joined._jdf.queryExecution().executedPlan().toString()


def test_clients_and_verifiers(spark):
    assert last_program("x ```py\na\n``` ```\nb\n```") == "b\n" and last_program("```py\nnever closed") is None
    rows = spark.createDataFrame([(1, "```\nreturn 42\n```", "42"), (2, "no program 42", "42"), (3, None, "42"), (4, "```\n421\n```", "42"), (5, "```\n42\n```", None)], "id long, response string, truth string")
    assert [r.id for r in verify(rows, ProgramVerifier(StubSandbox())).filter("passed").collect()] == [1]
    calls = rows.select("id", F.lit("q").alias("question"), F.lit("start").alias("response"))
    told = {r.id: (r.attempts, r.passed) for r in verify_regenerate(calls, "id", StubClient(), lambda ids, responses, attempt: [int(i) <= attempt + 0 and int(i) < 5 for i in ids], 4).collect()}
    assert told == {1: (1, True), 2: (2, True), 3: (3, True), 4: (4, True), 5: (4, False)}
    texts = spark.createDataFrame([(1, "prove the theorem, then the equation", "x"), (2, "a function returns an array", "y"), (3, None, "z")], "id long, text string, source string")
    assert [r.domain for r in annotate_domain(texts, "lexicon", "text", default="other").orderBy("id").collect()] == ["math", "code", "other"]
    shaped = spark.createDataFrame([("math", r"so \boxed{1}."), ("math", "so 1."), ("code", "```\nx\n```"), ("science", "never closed"), ("science", None)], "d string, r string")
    assert [r[0] for r in shaped.select(format_reasons(F.col("r"), F.col("d"))).collect()] == [[], ["no_boxed_answer"], [], ["incomplete"], ["empty", "incomplete"]]


def test_scores(spark, sf):
    import zlib

    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(20)
    text = {r.doc_id: r.text for r in docs.collect()}
    assert all(r.ratio == len(zlib.compress(text[r.doc_id].encode())) / max(1, len(text[r.doc_id].encode())) for r in score_compression(docs, "doc_id", "text").collect())
    assert tuple(step_work(docs, "text").first()) == (20, sum(len(t.encode()) for t in text.values()))


def test_learned_judge(spark):
    good, bad = "clear steps lead to the answer", "buy now click here spam"
    docs = spark.createDataFrame([(i, f"{good if i % 2 else bad} {i % 7}") for i in range(200)], "doc_id long, text string")
    labels = docs.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("quality"))
    assert quality_scores(docs, labels).first().auc > 0.99


def test_mix_keeps_the_ratio(spark):
    weights = {"math": 4, "code": 4, "science": 3}
    assert ratio_budget({"math": 100, "code": 8, "science": 50}, weights) == 22 and ratio_budget({"math": 5}, weights) == 5 and ratio_budget({}, weights) == 0
    rows = spark.range(300).select(F.col("id"), F.when(F.col("id") < 100, "math").when(F.col("id") < 108, "code").when(F.col("id") < 290, "science").alias("domain"))
    assert collections.Counter(r.domain for r in mix(rows, weights, None, [F.col("id")]).collect()) == {"math": 8, "code": 8, "science": 6}


def test_missing_texts_are_distilled(spark):
    docs = spark.createDataFrame([(1, "there", 5), (2, None, None)], "doc_id long, text string, n_chars long")
    got = {r.doc_id: (r.text, r.n_chars) for r in distilled(docs, StubClient()).collect()}
    assert got[1] == ("there", 5) and got[2][0].startswith("stub:") and got[2][1] == len(got[2][0])


def test_ingest_of_a_new_source(spark):
    words = lambda name: " ".join(f"{name}{i}" for i in range(30))
    held = spark.createDataFrame([(1, words("a"))], "doc_id long, text string")
    from sparkcurate.functions.text import grams

    bench = spark.createDataFrame([(1, words("b"))], "item_id long, text string")
    new = spark.createDataFrame([(2, words("a")), (3, words("b")), (4, words("c"))], "doc_id long, text string")
    accepted, after = ingest(new, grams(held, "doc_id", "text", 20).select("gram"), bench)
    assert [r.doc_id for r in accepted.collect()] == [4] and after.count() == 22


def test_streams(spark, tmp_path):
    rows = [(i, f"2024-01-{1 + i // 4:02d} 10:00:00", "ab"[i % 2], float(i * 7 % 10)) for i in range(40)]
    late = [(100, "2024-01-01 00:00:00", "a", 99.0)]
    # a row is late by the watermark of the batch before its own
    for k, some in enumerate((rows, [(200, "2024-01-30 00:00:00", "b", 1.0)], late)):
        spark.createDataFrame(some, "event_id long, at string, event_type string, value double").selectExpr("event_id", "cast(at as timestamp) ts", "event_type", "value").coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / f"{k}"))
    schema = spark.read.parquet(str(tmp_path / "in" / "0")).schema
    stream = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("latestFirst", "false").parquet(str(tmp_path / "in"))
    read, dropped = st.drained_progress(st.tumbling(stream()), "append")
    assert read == 42 and dropped == 1
    best = st.fill_quota(stream().select("event_type", "event_id", "value"), str(tmp_path / "quota"), "event_type", [F.desc("value"), F.col("event_id")], 3)
    assert {(r.event_type, r.event_id) for r in best.collect()} == {(t, i) for t in "ab" for *_, i in sorted((-v, i) for i, _, u, v in [*rows, *late, (200, "", "b", 1.0)] if u == t)[:3]}
    assert collections.Counter(r.event_type for r in st.drain(st.accept_within_quota(stream().select("event_type", "event_id"), "event_type", "event_id", 7), "append").collect()) == {"a": 7, "b": 7}


def test_drained_rows_lie_in_files(spark, tmp_path):
    rows = spark.range(30).selectExpr("id % 20 AS event_id", "timestamp'2024-01-01 00:00:00' AS ts", "'a' AS event_type", "1.0D AS value")
    for k in range(3):
        rows.filter(f"event_id % 3 = {k}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = lambda: spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    once = st.drain(st.distinct_events(stream()).select("event_id"), "append")
    assert sorted(r.event_id for r in once.collect()) == list(range(20)) and once.inputFiles()
    days = st.drain(st.tumbling(stream()))
    assert [(r.event_type, r.n, r.total) for r in days.collect()] == [("a", 30, 30.0)] and days.inputFiles()
    (tmp_path / "none").mkdir()
    none = st.drain(st.tumbling(spark.readStream.schema(rows.schema).parquet(str(tmp_path / "none"))))
    assert none.count() == 0 and none.columns == ["w", "event_type", "n", "total"]


@pytest.mark.parametrize("parts", [1, 2])
def test_streams_read_a_file_and_a_folder(spark, tmp_path, parts):
    item = " ".join(f"w{i}" for i in range(16))
    docs = spark.createDataFrame([(1, item), (2, "else " + item[:-4]), (3, None), (4, "w1 w2")], "doc_id long, text string")
    for name, rows in (("documents", docs), ("benchmark", spark.createDataFrame([(1, item)], "item_id long, text string"))):
        rows.repartition(parts, rows.columns[0]).write.parquet(str(tmp_path / "in" / f"{name}.parquet"))
    if parts == 1:
        (tmp_path / "one").mkdir()
        for name in ("documents", "benchmark"):
            next((tmp_path / "in" / f"{name}.parquet").glob("part-*.parquet")).rename(tmp_path / "one" / f"{name}.parquet")
    at = str(tmp_path / ("one" if parts == 1 else "in"))
    assert {(r.doc_id, r.hits) for r in decontaminate(spark, at).collect()} == {(1, 2), (2, 1)}
