"""Sampling, mixes, curriculum, preferences, strategies and ablations."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import grams, hex_number, seeded
from sparkcurate.operators import difficulty as di
from sparkcurate.operators import mix as mx
from sparkcurate.operators import prefs as pr
from sparkcurate.operators import select as se
from sparkcurate.operators.decontam import contaminated_any
from sparkcurate.operators.evaluate import events_as_runs
from sparkcurate.operators.rules import annotate_domain, filter_keywords
from sparkcurate.plans import oracle_text as o
from sparkcurate.plans import strategies as st
from sparkcurate.plans.pipeline import Config, ingest, run_pipeline
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import documents_as_qa, table

_DOCS = f"docs AS (SELECT doc_id, {o.DOMAIN} AS domain, source AS category, n_chars, {o.RND} AS rnd FROM documents)"


def _docs(spark, d):
    docs = annotate_domain(table(spark, d, "documents")).select("doc_id", "domain", "category", "n_chars")
    return docs.withColumn("rnd", seeded("doc_id"))


def _rnd():
    return [F.col("rnd"), F.col("doc_id")]


def _longest():
    return [F.desc("n_chars"), F.col("doc_id")]


@query("m08_balanced_category", f"WITH {_DOCS}, s AS ({o.balanced('docs', 'category', 'rnd, doc_id', 150)}) SELECT doc_id, category FROM docs JOIN s USING (doc_id)")
def m08(spark, d):
    return se.sample_balanced(_docs(spark, d), "category", 150, _rnd()).select("doc_id", "category")


@query("m08_balanced_language", f"SELECT doc_id FROM (SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY {o.RND}, doc_id) AS rn FROM documents WHERE lang IN ('en', 'es', 'fr')) ORDER BY rn, lang LIMIT 500")
def m08_language(spark, d):
    docs = table(spark, d, "documents").filter(F.col("lang").isin("en", "es", "fr")).select("doc_id", "lang").withColumn("rnd", seeded("doc_id"))
    return se.sample_balanced(docs, "lang", 500, _rnd()).select("doc_id")


@query("m08b_nested", f"""WITH {_DOCS}, r1 AS (SELECT *, row_number() OVER (PARTITION BY domain, category ORDER BY rnd, doc_id) AS ri FROM docs),
r2 AS (SELECT *, row_number() OVER (PARTITION BY domain ORDER BY ri, category) AS ro FROM r1) SELECT doc_id, domain, category FROM r2 ORDER BY ro, domain LIMIT 100""")
def m08b(spark, d):
    return se.sample_nested(_docs(spark, d), "domain", "category", 100, _rnd()).select("doc_id", "domain", "category")


@query("m11_balanced_cluster", f"WITH e AS (SELECT vec_id, label, md5(concat_ws(':', '42', CAST(vec_id AS VARCHAR))) AS rnd FROM embeddings) {o.balanced('e', 'label', 'rnd, vec_id', 85, 'vec_id')}")
def m11(spark, d):
    vectors = table(spark, d, "embeddings").select("vec_id", "label").withColumn("rnd", seeded("vec_id"))
    return se.sample_balanced(vectors, "label", 85, [F.col("rnd"), F.col("vec_id")]).select("vec_id")


@query("m12_merge", f"""WITH {_DOCS}, a AS ({o.balanced('docs', 'category', 'rnd, doc_id', 60)}), b AS ({o.balanced('docs', 'domain', 'n_chars DESC, doc_id', 60)})
SELECT doc_id, doc_id IN (SELECT doc_id FROM a) AS from_domain, doc_id IN (SELECT doc_id FROM b) AS from_semantic FROM (SELECT doc_id FROM a UNION SELECT doc_id FROM b)""")
def m12(spark, d):
    docs = _docs(spark, d)
    return se.merge_selections(se.sample_balanced(docs, "category", 60, _rnd()), se.sample_balanced(docs, "domain", 60, _longest()), "doc_id")


@query("m12_merge_topup", f"WITH {_DOCS}, x AS (SELECT *, domain AS cluster FROM docs) SELECT doc_id FROM {o.dual('x', 'n_chars DESC, doc_id', 120)}")
def m12_topup(spark, d):
    return se.dual(_docs(spark, d), "doc_id", "category", "domain", 120, _longest()).select("doc_id")


@query("m14_length_levels", f"WITH x AS (SELECT doc_id, len({o.tok('text')}) AS difficulty FROM documents) SELECT doc_id, CAST(difficulty AS BIGINT) AS difficulty, ntile(4) OVER (ORDER BY difficulty, doc_id) AS level FROM x")
def m14(spark, d):
    scored = di.score_length(table(spark, d, "documents")).select("doc_id", "difficulty")
    return di.difficulty_level(scored, "difficulty", "doc_id").withColumn("level", F.col("level").cast("long"))


@query("m14_levels_by_cuts", "WITH c AS (SELECT quantile_disc(n_chars, [0.25, 0.5, 0.75]) AS q FROM documents) SELECT CAST(1 + len(list_filter(q, lambda x: x < n_chars)) AS INTEGER) AS level, count(*) AS n FROM documents, c GROUP BY 1")
def m14_cuts(spark, d):
    return di.difficulty_level_by_cuts(table(spark, d, "documents").select("doc_id", "n_chars"), "n_chars").groupBy("level").agg(F.count(F.lit(1)).alias("n"))


@query("m14b_longest_in_category", f"WITH {_DOCS} {o.balanced('docs', 'category', 'n_chars DESC, doc_id', 90)}")
def m14b(spark, d):
    return se.sample_balanced(_docs(spark, d), "category", 90, _longest()).select("doc_id")


@query("m14c_easy", f"WITH {_DOCS} {o.balanced('docs', 'category', 'n_chars, doc_id', 90)}")
def m14c(spark, d):
    return se.sample_balanced(_docs(spark, d), "category", 90, [F.col("n_chars"), F.col("doc_id")]).select("doc_id")


_MIX = "SELECT doc_id, domain FROM (SELECT *, (2 * row_number() OVER (PARTITION BY domain ORDER BY rnd, doc_id) - 1) * CASE domain WHEN 'science' THEN 4 ELSE 3 END AS k FROM docs) ORDER BY k, domain LIMIT {}"


@query("m23_mix_443", f"WITH {_DOCS} {_MIX.format(550)}")
def m23(spark, d):
    return mx.mix(_docs(spark, d), {"math": 4, "code": 4, "science": 3}, 550, _rnd()).select("doc_id", "domain")


@query("m23b_counts", f"WITH {_DOCS} SELECT doc_id, domain FROM (SELECT *, row_number() OVER (PARTITION BY domain ORDER BY rnd, doc_id) AS rn FROM docs) WHERE rn <= CASE domain WHEN 'math' THEN 40 WHEN 'code' THEN 30 ELSE 20 END")
def m23b(spark, d):
    return mx.mix_counts(_docs(spark, d), {"math": 40, "code": 30, "science": 20}, _rnd()).select("doc_id", "domain")


_STAGE = "SELECT doc_id, CASE WHEN row_number() OVER (ORDER BY {}) <= floor((SELECT count(*) FROM docs) * 0.7 + 1e-9) THEN 1 ELSE 2 END AS stage FROM docs"


@query("m24_curriculum", f"WITH {_DOCS} " + _STAGE.format("CASE WHEN domain IN ('math', 'code') THEN 0 ELSE 1 END, n_chars, doc_id"))
def m24(spark, d):
    return mx.curriculum(_docs(spark, d), "doc_id", "n_chars").select("doc_id", "stage")


@query("m24b_length_only", f"WITH {_DOCS} " + _STAGE.format("n_chars, doc_id"))
def m24b(spark, d):
    return mx.curriculum(_docs(spark, d), "doc_id", "n_chars", priority=()).select("doc_id", "stage")


@query("w09_curriculum", f"WITH {_DOCS}, s AS ({_STAGE.format("CASE WHEN domain IN ('math', 'code') THEN 0 ELSE 1 END, n_chars, doc_id")}) SELECT stage, domain, count(*) AS n, max(n_chars) AS longest FROM s JOIN docs USING (doc_id) GROUP BY ALL")
def w09(spark, d):
    return mx.curriculum(_docs(spark, d), "doc_id", "n_chars").groupBy("stage", "domain").agg(F.count(F.lit(1)).alias("n"), F.max("n_chars").alias("longest"))


# the tuning set of the preference queries: the mix of 200
_TUNED = f"{_DOCS}, tuned AS ({_MIX.format(200)})"
_CROSS = f"{_TUNED}, {o.grams('g', 'documents', 'doc_id', 20)}, tg AS (SELECT DISTINCT gram FROM g WHERE doc_id IN (SELECT doc_id FROM tuned)), near AS (SELECT DISTINCT doc_id FROM g WHERE gram IN (SELECT gram FROM tg))"
_CAND = f"{_CROSS}, {o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)}, cand AS (SELECT * FROM docs WHERE doc_id NOT IN (SELECT doc_id FROM near) AND doc_id NOT IN (SELECT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg)))"


def _tuned(spark, d):
    ids = mx.mix(_docs(spark, d), {"math": 4, "code": 4, "science": 3}, 200, _rnd()).select("doc_id")
    return table(spark, d, "documents").join(ids, "doc_id", "left_semi").select("doc_id", "text")


def _candidates(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "text")
    kept = pr.candidates(docs, _tuned(spark, d), contaminated_any(docs, table(spark, d, "benchmark"), "doc_id"), "doc_id")
    return _docs(spark, d).join(kept.select("doc_id"), "doc_id", "left_semi")


@query("m25_cross_overlap", f"WITH {_CROSS} SELECT doc_id FROM near")
def m25(spark, d):
    return pr.overlap_with(table(spark, d, "documents").select("doc_id", "text"), _tuned(spark, d), "doc_id")


@query("m25_candidates", f"WITH {_CAND} SELECT doc_id FROM cand")
def m25_candidates(spark, d):
    return _candidates(spark, d).select("doc_id")


@query("m26_longest", f"WITH {_DOCS} SELECT doc_id, domain, category FROM (SELECT *, row_number() OVER (PARTITION BY domain, category ORDER BY n_chars DESC, doc_id) AS rn FROM docs) WHERE rn <= 10")
def m26(spark, d):
    return pr.select_longest(_docs(spark, d), ["domain", "category"], 10, "n_chars", "doc_id").select("doc_id", "domain", "category")


def _false(df):
    """Stand-in verdict on the policy's answer: false for seven digests in sixteen."""
    return df.filter(hex_number(seeded("doc_id", 9), 1, 1) < 7)


_FALSE = "CAST('0x' || substr(md5(concat_ws(':', '9', CAST(doc_id AS VARCHAR))), 1, 1) AS INTEGER) < 7"


@query("m27_policy_answers", "SELECT doc_id, 'stub:' || md5(CAST(doc_id AS VARCHAR) || ':1') AS response FROM documents")
def m27(spark, d):
    from sparkcurate.operators.quality import StubClient, distill

    asked = table(spark, d, "documents").select(F.col("doc_id").alias("qid"), F.col("text").alias("question"), F.lit(None).cast("string").alias("response"))
    return distill(asked, StubClient()).select(F.col("qid").alias("doc_id"), "response")


@query("m28_false", f"WITH {_DOCS} SELECT doc_id FROM docs WHERE {_FALSE}")
def m28(spark, d):
    return _false(_docs(spark, d)).select("doc_id")


@query("m29_balanced_false", f"WITH {_DOCS}, f AS (SELECT * FROM docs WHERE {_FALSE}), r AS (SELECT *, row_number() OVER (PARTITION BY domain, category ORDER BY n_chars DESC, doc_id) AS rn FROM f) SELECT doc_id, domain, category FROM r WHERE rn <= 3")
def m29(spark, d):
    return pr.select_longest(_false(_docs(spark, d)), ["domain", "category"], 3, "n_chars", "doc_id").select("doc_id", "domain", "category")


@query("m30_pairs", f"WITH {_DOCS}, f AS (SELECT * FROM docs WHERE {_FALSE}) SELECT doc_id, domain, category, CAST(length(text) AS BIGINT) AS chosen_chars, 'stub:' || md5(CAST(doc_id AS VARCHAR) || ':1') AS rejected FROM f JOIN documents USING (doc_id)")
def m30(spark, d):
    from sparkcurate.operators.quality import StubClient, distill

    strong = documents_as_qa(table(spark, d, "documents"))
    asked = _false(_docs(spark, d)).select(F.col("doc_id").alias("qid"), F.lit("").alias("question"), F.lit(None).cast("string").alias("response"))
    made = pr.build_pairs(strong, distill(asked, StubClient()).select("qid", "response"), "qid")
    return made.select(F.col("qid").alias("doc_id"), "domain", "category", F.length("chosen").cast("long").alias("chosen_chars"), "rejected")


def _preference(counts: str) -> str:
    return f"""WITH {_CAND}, l AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY domain, category ORDER BY n_chars DESC, doc_id) AS rn FROM cand) WHERE rn <= 20),
f AS (SELECT doc_id, domain, category, n_chars FROM l WHERE {_FALSE}), b AS (SELECT *, row_number() OVER (PARTITION BY domain, category ORDER BY n_chars DESC, doc_id) AS rc FROM f),
r AS (SELECT *, row_number() OVER (PARTITION BY domain ORDER BY rc, category) AS rd FROM b) SELECT doc_id, domain, category FROM r WHERE rd <= CASE domain {counts} END"""


def _run_preference(spark, d, counts):
    """Candidates, longest strong solutions, false answers, balanced by category in each domain's count."""
    longest = pr.select_longest(_candidates(spark, d), ["domain", "category"], 20, "n_chars", "doc_id")
    false = cut(_false(longest))
    out = None
    for domain, budget in counts.items():
        rows = se.sample_balanced(false.filter(F.col("domain") == domain), "category", budget, _longest()).select("doc_id", "domain", "category")
        out = rows if out is None else out.unionByName(rows)
    return out


@query("w08_preference_9k", _preference("WHEN 'math' THEN 40 WHEN 'code' THEN 30 ELSE 20"))
def w08_small(spark, d):
    return _run_preference(spark, d, {"math": 40, "code": 30, "science": 20})


@query("w08_preference_10k", _preference("WHEN 'math' THEN 35 WHEN 'code' THEN 35 ELSE 30"))
def w08_large(spark, d):
    return _run_preference(spark, d, {"math": 35, "code": 35, "science": 30})


_LOGP = """cnt AS (SELECT q, w, count(*) AS c FROM (SELECT CASE WHEN quality = 1 THEN 1 ELSE 0 END AS q, unnest({t}) AS w FROM documents LEFT JOIN labels USING (doc_id)) GROUP BY ALL),
pol AS (SELECT w, c FROM cnt WHERE q = 1), ref AS (SELECT w, sum(c) AS c FROM cnt GROUP BY w), pt AS (SELECT sum(c) AS n, count(*) AS k FROM pol), rt AS (SELECT sum(c) AS n, count(*) AS k FROM ref),
own AS (SELECT doc_id, w, count(*) AS n FROM (SELECT doc_id, unnest({t}) AS w FROM documents) GROUP BY ALL),
lp AS (SELECT doc_id, round(sum(own.n * ln((coalesce(pol.c, 0) + 1) / (pt.n + pt.k + 1))) / sum(own.n), 6) AS pol, round(sum(own.n * ln((coalesce(ref.c, 0) + 1) / (rt.n + rt.k + 1))) / sum(own.n), 6) AS ref
  FROM own LEFT JOIN pol USING (w) LEFT JOIN ref USING (w) CROSS JOIN pt CROSS JOIN rt GROUP BY doc_id)""".replace("{t}", o.tok("text"))


def _logprobs(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "text")
    good = docs.join(table(spark, d, "labels").filter("quality = 1").select("doc_id"), "doc_id", "left_semi")
    policy = di.unigram_logprob(docs, "doc_id", "text", good, "text").withColumnRenamed("logprob", "pol")
    return policy.join(di.unigram_logprob(docs, "doc_id", "text", docs, "text").withColumnRenamed("logprob", "ref"), "doc_id")


# chosen: the record itself; rejected: the record with the next id
_LOSS = f"""WITH {_LOGP}, m AS (SELECT 0.1 * ((a.pol - a.ref) - (b.pol - b.ref)) AS m FROM lp a JOIN lp b ON b.doc_id = a.doc_id + 1)
SELECT round(avg(greatest(-m, 0) + ln(1 + exp(-abs(m)))), 6) AS loss, round(avg(m), 6) AS margin, round(avg(CAST(m > 0 AS INTEGER)), 6) AS accuracy, count(*) AS n FROM m"""


@query("w14_loss", _LOSS)
def w14(spark, d):
    lp = _logprobs(spark, d)
    sides = lp.select("doc_id", F.col("pol").alias("pol_chosen"), F.col("ref").alias("ref_chosen")).join(lp.select((F.col("doc_id") - 1).alias("doc_id"), F.col("pol").alias("pol_rejected"), F.col("ref").alias("ref_rejected")), "doc_id")
    return pr.preference_loss(sides).select(*[F.round(c, 6).alias(c) for c in ("loss", "margin", "accuracy")], "n")


_LOGPROBS = {"pol_chosen": 17, "ref_chosen": 19, "pol_rejected": 23, "ref_rejected": 29}


@query("m31_loss", f"WITH x AS (SELECT {', '.join(f'-(n_chars % {k}) / 2.0 AS {c}' for c, k in _LOGPROBS.items())} FROM documents), m AS (SELECT 0.1 * ((pol_chosen - ref_chosen) - (pol_rejected - ref_rejected)) AS m FROM x) SELECT round(avg(ln(1 + exp(-m))), 6) AS loss, round(avg(m), 6) AS margin, round(avg(CASE WHEN m > 0 THEN 1.0 ELSE 0.0 END), 6) AS accuracy, count(*) AS n FROM m")
def m31(spark, d):
    """Log-probabilities made of remainders of the length, so that margins have both signs."""
    made = table(spark, d, "documents").select(*[(-(F.col("n_chars") % k) / 2.0).alias(c) for c, k in _LOGPROBS.items()])
    return pr.preference_loss(made).select(F.round("loss", 6).alias("loss"), F.round("margin", 6).alias("margin"), F.round("accuracy", 6).alias("accuracy"), "n")


_NAMES = {"random": "b01_random", "dual": "b03_dual", "length": "b04_length", "complexity+dual": "b05_complexity_dual", "ifd+dual": "b06_ifd_dual", "length+embedding": "b07_length_embedding", "length+category": "b08_length_category", "length+dual": "b09_length_dual"}

for _strategy, _name in _NAMES.items():

    @query(_name, f"WITH {o.SCORED} SELECT doc_id FROM {o.strategy(_strategy, 100)}")
    def _one(spark, d, s=_strategy):
        return st.select(st.scored_documents(table(spark, d, "documents")), s, 100)


@query("b02_random_three_seeds", " UNION ALL ".join(f"(SELECT {s} AS seed, doc_id FROM documents ORDER BY md5(concat_ws(':', '{s}', CAST(doc_id AS VARCHAR))), doc_id LIMIT 20)" for s in (42, 43, 44)))
def b02(spark, d):
    docs = table(spark, d, "documents").select("doc_id")
    each = docs.withColumn("seed", F.explode(F.array(*[F.lit(s) for s in (42, 43, 44)]))).withColumn("rnd", F.md5(F.concat_ws(":", F.col("seed").cast("string"), F.col("doc_id").cast("string"))))
    return se.top_per_group(each, ["seed"], _rnd(), 20).select("seed", "doc_id")


_SUB = "WITH {scored}, sub AS (SELECT * FROM scored WHERE {where}) SELECT doc_id FROM {law}"


def _where(spark, d, where):
    return st.scored_documents(table(spark, d, "documents")).filter(where)


@query("b10_easy_diverse", _SUB.format(scored=o.SCORED, where="category = 'src0'", law=o.dual("sub", "n_chars, doc_id", 20)))
def b10_easy(spark, d):
    return st.select(_where(spark, d, "category = 'src0'"), "length+dual", 20, ascending=True)


@query("b10_hard_diverse", _SUB.format(scored=o.SCORED, where="category = 'src0'", law=o.dual("sub", "n_chars DESC, doc_id", 20)))
def b10_hard(spark, d):
    return st.select(_where(spark, d, "category = 'src0'"), "length+dual", 20)


@query("b11_mix_hard", _SUB.format(scored=o.SCORED, where="category IN ('src0', 'src3')", law=o.dual("sub", "n_chars DESC, doc_id", 20)))
def b11(spark, d):
    return st.select(_where(spark, d, "category IN ('src0', 'src3')"), "length+dual", 20)


_RUNS = """runs AS (SELECT CASE WHEN event_id % 2 = 0 THEN 'even' ELSE 'odd' END AS model, CAST(json_extract(props, '$.k') AS INTEGER) % 6 AS benchmark, user_id AS problem_id, event_type IN ('purchase', 'signup') AS correct,
row_number() OVER (PARTITION BY event_id % 2, CAST(json_extract(props, '$.k') AS INTEGER) % 6, user_id ORDER BY ts, event_id) AS run_id FROM events)"""


@query("b12_teacher_swap", f"WITH {_DOCS} SELECT doc_id, 'stub:' || md5(CAST(doc_id AS VARCHAR) || ':1') AS response FROM docs ORDER BY rnd, doc_id LIMIT 50")
def b12(spark, d):
    """The same prompts, answered again by another teacher."""
    from sparkcurate.operators.quality import StubClient, distill

    fixed = se.first_rows(_docs(spark, d), _rnd(), 50)
    asked = fixed.select(F.col("doc_id").alias("qid"), F.lit("").alias("question"), F.lit(None).cast("string").alias("response"))
    return distill(asked, StubClient()).select(F.col("qid").alias("doc_id"), "response")


@query("b13_pass_at_k", f"""WITH {_RUNS}, p AS (SELECT benchmark, problem_id, count(*) AS n, count(*) FILTER (WHERE correct) AS c FROM runs GROUP BY ALL)
SELECT benchmark, problem_id, n, c, CASE WHEN n < 2 THEN NULL WHEN n - c < 2 THEN 1.0 ELSE round(1 - (CAST(n - c AS DOUBLE) / n) * (CAST(n - c - 1 AS DOUBLE) / (n - 1)), 6) END AS pass2 FROM p""")
def b13(spark, d):
    per = events_as_runs(table(spark, d, "events")).groupBy("benchmark", "problem_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("correct").cast("long")).alias("c"))
    return per.withColumn("pass2", F.round(di.pass_at_k(F.col("n"), F.col("c"), 2), 6))


@query("b14_keywords", f"SELECT doc_id FROM documents WHERE len(list_intersect({o.tok('text')}, ['license', 'copyright', 'idiot'])) = 0")
def b14(spark, d):
    return filter_keywords(table(spark, d, "documents"), ("license", "copyright", "idiot")).select("doc_id")


@query("b15_compression")
def b15(spark, d):
    return di.score_compression(table(spark, d, "documents"), "doc_id", "text").select("doc_id", F.round("ratio", 6).alias("ratio"))


@query("b05_complexity_score", f"WITH {o.SCORED} SELECT doc_id, complexity FROM scored")
def b05_score(spark, d):
    return st.scored_documents(table(spark, d, "documents")).select("doc_id", "complexity")


@query("b06_ifd_score", f"WITH {o.SCORED} SELECT doc_id, ifd FROM scored")
def b06_score(spark, d):
    return st.scored_documents(table(spark, d, "documents")).select("doc_id", "ifd")


_SUMMARY = "SELECT strategy, count(*) AS n, round(avg(n_chars), 6) AS mean_chars, count(DISTINCT category) AS categories, count(DISTINCT cluster) AS clusters, round(avg(complexity), 6) AS mean_complexity, round(avg(ifd), 6) AS mean_ifd FROM sel JOIN scored USING (doc_id) GROUP BY strategy"
_ALL = "sel AS (" + " UNION ALL ".join(f"SELECT '{s}' AS strategy, doc_id FROM {o.strategy(s, 100)}" for s in st.STRATEGIES) + ")"


@query("w02_ablation", f"WITH {o.SCORED}, {_ALL} {_SUMMARY}")
def w02(spark, d):
    scored = st.scored_documents(table(spark, d, "documents"))
    return st.summary(st.run_ablation(scored, st.STRATEGIES, 100), scored)


@query("s07_strategy_overlap", f"WITH {o.SCORED}, {_ALL}, n AS (SELECT strategy, count(*) AS n FROM sel GROUP BY strategy), q AS (SELECT a.n AS na, b.n AS nb, a.strategy AS a, b.strategy AS b, (SELECT count(*) FROM sel x JOIN sel y USING (doc_id) WHERE x.strategy = a.strategy AND y.strategy = b.strategy) AS \"both\", 0.0 AS jaccard FROM n a JOIN n b ON a.strategy < b.strategy) SELECT a, b, \"both\", round(\"both\" / (na + nb - \"both\"), 6) AS jaccard FROM q")
def s07_overlap(spark, d):
    from sparkcurate.operators.evaluate import strategy_overlap

    return strategy_overlap(st.run_ablation(st.scored_documents(table(spark, d, "documents")), st.STRATEGIES, 100), "doc_id")


_SCIENCE = ("random", "dual", "length", "length+dual")
_SCI_LAWS = {"random": "(SELECT doc_id FROM sub ORDER BY rnd, doc_id LIMIT 40)", "dual": o.dual("sub", "rnd, doc_id", 40), "length": "(SELECT doc_id FROM sub ORDER BY n_chars DESC, doc_id LIMIT 40)", "length+dual": o.dual("sub", "n_chars DESC, doc_id", 40)}


@query("w03_science", f"WITH {o.SCORED}, sub AS (SELECT * FROM scored WHERE domain = 'science'), sel AS (" + " UNION ALL ".join(f"SELECT '{s}' AS strategy, doc_id FROM {law}" for s, law in _SCI_LAWS.items()) + f") {_SUMMARY}")
def w03(spark, d):
    scored = _where(spark, d, "domain = 'science'")
    return st.summary(st.run_ablation(scored, _SCIENCE, 40), scored)


_MATH = {"a_easy": ("category = 'src0'", "n_chars, doc_id"), "a_hard": ("category = 'src0'", "n_chars DESC, doc_id"), "b_hard": ("category = 'src3'", "n_chars DESC, doc_id"), "mix_hard": ("category IN ('src0', 'src3')", "n_chars DESC, doc_id")}


@query("w04_math", f"WITH {o.SCORED}, " + ", ".join(f"sub_{k} AS (SELECT * FROM scored WHERE {w})" for k, (w, _) in _MATH.items()) + ", sel AS (" + " UNION ALL ".join(f"SELECT '{k}' AS strategy, doc_id FROM {o.dual(f'sub_{k}', order, 20)}" for k, (_, order) in _MATH.items()) + f") {_SUMMARY}")
def w04(spark, d):
    scored = st.scored_documents(table(spark, d, "documents"))
    out = None
    for name, (where, order) in _MATH.items():
        rows = cut(st.select(scored.filter(where), "length+dual", 20, ascending="DESC" not in order)).select(F.lit(name).alias("strategy"), "doc_id")
        out = rows if out is None else out.unionByName(rows)
    return st.summary(out, scored)


@query("w05_strict_pool")
def w05(spark, d):
    from sparkcurate.operators.semantic import strict_pool

    docs = table(spark, d, "documents")
    scored = st.scored_documents(docs.join(strict_pool(docs), "doc_id", "left_semi"), fitted=True)
    # 17 of 1,000 records, 20 at least
    budget = max(20, round(0.017 * scored.count()))
    out = cut(st.select(scored, "length+dual", budget)).select(F.lit("length+dual").alias("strategy"), "doc_id")
    for seed in (42, 43, 44):
        again = scored.withColumn("rnd", seeded("doc_id", seed))
        out = out.unionByName(cut(st.select(again, "random", budget)).select(F.lit(f"random-{seed}").alias("strategy"), "doc_id"))
    return st.summary(out, scored)


@query("w01_pipeline")
def w01(spark, d):
    return run_pipeline(spark, d)[0].select("doc_id", "domain", "category", "n_chars", "stage")


@query("w01_pipeline_report")
def w01_report(spark, d):
    return run_pipeline(spark, d, Config(share=0.08, order="early"))[1]


@query("m33_nested_budgets", f"WITH {_DOCS}, a AS ({o.balanced('docs', 'category', 'rnd, doc_id', 80)}), b AS ({o.balanced('docs', 'category', 'rnd, doc_id', 150)}) SELECT (SELECT count(*) FROM a) AS small, (SELECT count(*) FROM b) AS large, (SELECT count(*) FROM a WHERE doc_id IN (SELECT doc_id FROM b)) AS nested")
def m33(spark, d):
    docs = _docs(spark, d)
    small, large = se.sample_balanced(docs, "category", 80, _rnd()).select("doc_id", F.lit(1).alias("s")), se.sample_balanced(docs, "category", 150, _rnd()).select("doc_id", F.lit(1).alias("l"))
    both = small.join(large, "doc_id", "full")
    return both.agg(F.count("s").alias("small"), F.count("l").alias("large"), F.count(F.when(F.col("s").isNotNull() & F.col("l").isNotNull(), 1)).alias("nested"))


@query("m34_ingest", f"""WITH {o.grams('g', 'documents', 'doc_id', 20)}, {o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)}, old AS (SELECT DISTINCT gram FROM g JOIN documents USING (doc_id) WHERE source <> 'src1')
SELECT doc_id FROM documents WHERE source = 'src1' AND doc_id NOT IN (SELECT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg)) AND doc_id NOT IN (SELECT doc_id FROM g WHERE gram IN (SELECT gram FROM old))""")
def m34(spark, d):
    docs = table(spark, d, "documents")
    held = grams(docs.filter("source <> 'src1'"), "doc_id", "text", 20).select("gram").distinct()
    return ingest(docs.filter("source = 'src1'").select("doc_id", "text"), held, table(spark, d, "benchmark"))[0].select("doc_id")


@query("flagship_slice", f"""WITH c AS (SELECT doc_id, source AS category, n_chars FROM documents WHERE lang = 'en' AND len({o.tok('text')}) >= 5 AND regexp_matches(trim(text), '[.!?]$')),
s AS ({o.balanced('c', 'category', 'n_chars DESC, doc_id', 60)}), {o.grams('bg', 'benchmark', 'item_id', 15)}, {o.grams('dg', 'documents', 'doc_id', 15)}
SELECT doc_id, category, n_chars FROM c WHERE doc_id IN (SELECT doc_id FROM s) AND doc_id NOT IN (SELECT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg))""")
def flagship_slice(spark, d):
    from sparkcurate.plans.pipeline import minimum_slice

    return minimum_slice(spark, d)

