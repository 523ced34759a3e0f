import math

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from sparkcurate.operators.components import connected_components
from sparkcurate.operators.dedup import dedup_minhash, drop_by_pairs, duplicate_groups, overlap_pairs
from sparkcurate.operators.difficulty import pass_at_k
from sparkcurate.operators.evaluate import baseline_table, published_table, table_check, training_record
from sparkcurate.operators.mix import apportion, curriculum
from sparkcurate.operators.prefs import build_pairs, preference_loss
from sparkcurate.operators.quality import boxed_answer, normal_number
from sparkcurate.operators.select import quotas, sample_balanced
from sparkcurate.operators.semantic import similar_vectors, strict_pool
from sparkcurate.plans.pipeline import Config, contaminated, routed, run_pipeline
from sparkcurate.plans.strategies import fitted_clusters
from sparkcurate.sources.tables import read_files, write_files


def test_entry_and_registry(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_quotas_redistribute():
    assert quotas({"a": 1, "b": 3, "c": 100}, 6) == {"a": 1, "b": 3, "c": 2}
    assert quotas({"a": 1, "b": 3, "c": 100}, 50) == {"a": 1, "b": 3, "c": 46}
    assert sum(quotas({"a": 1, "b": 3, "c": 100}, 200).values()) == 104


def test_mix_ratio():
    many = {"math": 9999, "code": 9999, "science": 9999}
    weights = {"math": 4, "code": 4, "science": 3}
    assert apportion(many, weights, 550) == {"math": 200, "code": 200, "science": 150}
    assert apportion(many, weights, 11) == {"math": 4, "code": 4, "science": 3}
    assert sum(apportion({"math": 2, "code": 9999, "science": 1}, weights, 12).values()) == 12


def test_balance_is_stable_over_partitions(spark):
    rows = spark.range(900).select(F.col("id").alias("doc_id"), (F.col("id") % 7).cast("string").alias("g"), (F.col("id") * 37 % 101).alias("s"))
    sets = [{r.doc_id for r in sample_balanced(rows.repartition(n), "g", 70, [F.desc("s"), F.col("doc_id")]).collect()} for n in (1, 4, 16)]
    assert sets[0] == sets[1] == sets[2] and len(sets[0]) == 70


def test_chain_pair_and_group_semantics(spark):
    base = " ".join(f"w{i}" for i in range(100))
    texts = [(1, base), (2, base + " " + " ".join(f"x{i}" for i in range(18))), (3, " ".join(base.split()[15:]) + " " + " ".join(f"x{i}" for i in range(18)) + " y1 y2")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    pairs = overlap_pairs(docs, "doc_id", "text", 5, 0.8)
    assert {r.grp for r in duplicate_groups(docs, "doc_id", pairs).collect()} == {1}
    assert [r.doc_id for r in drop_by_pairs(docs, "doc_id", pairs).collect()] == [1]


def test_templates_survive_the_frequency_cap(spark):
    preamble = " ".join(f"p{i}" for i in range(25))
    rows = [(i, preamble + " " + " ".join(f"b{i}x{j}" for j in range(30))) for i in range(30)] + [(99, preamble + " " + " ".join(f"b3x{j}" for j in range(30)))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert [(r.a, r.b) for r in overlap_pairs(docs, "doc_id", "text", 20, 0.8, max_df=20).collect()] == [(3, 99)]


def test_sketches_find_all_containment_pairs(spark, sf):
    words = lambda name, n: [f"{name}{i}" for i in range(n)]
    body = words("w", 150)
    texts = [body, [*body[:140], *words("x", 12)], [*words("y", 12), *body[15:]], [*words("z", 200), *words("s", 40), *words("v", 200)], words("s", 40), ["a"] * 60, ["a"] * 70, words("q", 5), words("q", 5), []]
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    for rows in (docs, spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")):
        got = sorted(tuple(r) for r in dedup_minhash(rows, "doc_id", "text").collect())
        # a cap that no gram reaches: all pairs by a join of all grams
        assert got == sorted(tuple(r) for r in overlap_pairs(rows, "doc_id", "text", max_df=10**9).collect())
        assert rows is not docs or {(0, 1), (0, 2), (3, 4), (5, 6)} <= {r[:2] for r in got}


@pytest.mark.parametrize("block", [20_000, 40])
def test_similar_vectors_equal_brute_force(spark, block):
    rng = np.random.default_rng(4)
    base = rng.standard_normal((30, 100))
    x = np.concatenate([base + scale * rng.standard_normal(base.shape) for scale in (0, 0, 0.3, 0.45, 0.5, 0.7)]).astype(np.float32)
    x[-1] = 0
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    got = {(r.a, r.b) for r in similar_vectors(spark.createDataFrame(rows, "doc_id long, embedding array<float>"), "doc_id", block=block).collect()}
    unit = x.astype(float) / np.maximum(np.linalg.norm(x.astype(float), axis=1), 1e-9)[:, None]
    close = {(i, j) for i, j in zip(*np.nonzero(unit @ unit.T > 0.9), strict=True) if i < j}
    # ids 30 to 59 are copies of 0 to 29 and meet others through them
    assert got == {(i, j) for i, j in close if (i not in range(30, 60) and j not in range(30, 60)) or j == i + 30 and i < 30} and len(got) > 80
    assert similar_vectors(spark.createDataFrame([], "doc_id long, embedding array<float>"), "doc_id").count() == 0


def test_strict_pool_drops_short_copies(spark):
    docs = spark.createDataFrame([(1, "a short text"), (2, "A short text!"), (3, "another one here"), (4, None), (5, "")], "doc_id long, text string")
    assert sorted(r.doc_id for r in strict_pool(docs).collect()) == [1, 3, 4, 5]


def test_pipeline_samples_a_share_and_routes(spark, sf):
    final, report = run_pipeline(spark, sf)
    steps = {r.step: r.rows for r in report.collect()}
    assert steps["sampled"] == round(0.15 * steps["rules"]) and steps["verified"] < steps["format"] <= steps["overlap"]
    assert final.count() == steps["mixed"]


def test_pipeline_rejects_by_cosine_and_route(spark):
    item = "one two three four five six seven eight nine ten"
    docs = spark.createDataFrame([(1, item), (2, "quite another text of no item")], "doc_id long, text string")
    assert [r.doc_id for r in contaminated(docs, docs.limit(1).withColumnRenamed("doc_id", "item_id"), Config()).collect()] == [1]
    rows = [(i, "all words here differ from one another.", "math") for i in range(200)] + [(900, "all words here differ.", "science"), (901, "no " * 90 + "end.", "science"), (902, "never closed", "science")]
    shaped, passed = routed(spark.createDataFrame(rows, "doc_id long, text string, domain string"), Config())
    kept = {r.doc_id for r in passed.collect()}
    assert shaped.count() == 202 and kept - set(range(200)) == {900} and 150 < len(kept) < 201
    assert routed(spark.createDataFrame(rows, "doc_id long, text string, domain string"), Config(waived=()))[0].count() == 2


def test_fitted_clusters_of_copied_heads(spark):
    texts = ["red apples and green pears"] * 20 + ["fast cars on long roads"] * 20 + ["cold rain in dark woods"] * 20
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, question string")
    assert len({(r.cluster, texts[r.doc_id]) for r in fitted_clusters(rows, k=3).collect()}) == 3 == len({r.cluster for r in fitted_clusters(rows, k=3).collect()})


def test_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(50)] + [(100, 101), (102, 101)], "src long, dst long")
    got = {r.node: r.component for r in connected_components(edges).collect()}
    assert all(got[i] == 0 for i in range(51)) and {got[i] for i in (100, 101, 102)} == {100}
    assert connected_components(edges.limit(0)).count() == 0


def test_boxed_answers():
    assert boxed_answer(r"a \boxed{1} b \boxed{\frac{1}{2}}") == r"\frac{1}{2}" and boxed_answer(r"\boxed{1") is None and boxed_answer(None) is None
    assert normal_number(r"\frac{1}{2}") == normal_number("0.5") == normal_number("2/4") and normal_number("x + 1") == "x+1"


def loss(spark, *rows):
    return preference_loss(spark.createDataFrame([tuple(map(float, r)) for r in rows], "pol_chosen double, ref_chosen double, pol_rejected double, ref_rejected double")).first()


def test_preference_loss(spark):
    assert loss(spark, (0, 0, 0, 0)).loss == pytest.approx(math.log(2))
    up, down = loss(spark, (3, 0, 0, 0)), loss(spark, (0, 0, 3, 0))
    assert up.loss - down.loss == pytest.approx(-0.1 * 3) and up.accuracy == 1
    assert loss(spark, (1e5, 0, 0, 0)).loss == pytest.approx(0) and loss(spark, (0, 0, 1e5, 0)).loss == pytest.approx(1e4)


def test_equal_sides_fail(spark):
    strong = spark.createDataFrame([(1, "q", "same", "d", "c")], "qid long, question string, response string, domain string, category string")
    with pytest.raises(Exception, match="chosen equals rejected"):
        build_pairs(strong, strong.select("qid", "response"), "qid").collect()


def test_pass_at_k(spark):
    rows = spark.createDataFrame([(5, 2), (5, 0), (5, 5)], "n long, c long")
    assert [r[0] for r in rows.select(F.round(pass_at_k(F.col("n"), F.col("c"), 1), 9)).collect()] == [0.4, 0.0, 1.0]


def test_published_averages(spark):
    wrong = [r.model for r in table_check(published_table(spark)).collect() if not r.agrees]
    assert wrong == ["distilled_7b"]


def test_table_of_given_runs(spark, sf):
    runs = spark.createDataFrame([("a", b, u, r, (b + u + r) % 3 == 0) for b in range(6) for u in range(2) for r in (1, 2)], "model string, benchmark int, problem_id long, run_id int, correct boolean")
    shares = [25.0 * sum((b + u + r) % 3 == 0 for u in range(2) for r in ((1, 2) if b < 5 else (1,))) * (1 if b < 5 else 2) for b in range(6)]
    row = baseline_table(runs).first()
    assert tuple(row) == ("a", 22, *shares, round(sum(shares) / 6, 2)) and table_check(baseline_table(runs)).first().agrees
    for name in ("b16_baselines", "w11_table_check"):
        assert any("events.parquet" in f for f in __spark_entry__.queries()[name](spark, sf).inputFiles())


def test_training_record_counts_its_records(spark, sf):
    settings = spark.createDataFrame([("x", 3, 4), ("y", 2, 4)], "stage string, epochs int, batch int")
    texts = {"x": spark.createDataFrame([("ab",), (None,)] + [("c",)] * 4, "text string"), "y": spark.createDataFrame([], "text string")}
    assert sorted(map(tuple, training_record(settings, texts).collect())) == [("x", 3, 4, 5, 6, 6, 18), ("y", 2, 4, 0, None, 0, None)]
    read = " ".join(__spark_entry__.queries()["s10_training_record"](spark, sf).inputFiles())
    assert "documents.parquet" in read and "conversations.parquet" in read


def test_curriculum(spark):
    rows = spark.range(200).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "math").when(F.col("id") % 3 == 1, "code").otherwise("science").alias("domain"), (F.col("id") * 31 % 17).alias("n_chars"))
    got = curriculum(rows, "doc_id", "n_chars").toPandas()
    assert (got.stage == 1).sum() == 140 and len(got) == 200 and (got[got.stage == 1].domain == "science").sum() == 140 - (got.domain != "science").sum()


def test_formats(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a"), (2, "b")], "id long, t string")
    for form in ("parquet", "json", "csv", "orc"):
        write_files(rows, str(tmp_path / form), form)
        assert read_files(spark, str(tmp_path / form), form, "id long, t string").count() == 2
