"""Formatting, filters, overlap removal, decontamination, quality."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.text import domain_of_source
from sparkcurate.operators import cluster as cl
from sparkcurate.operators import decontam as de
from sparkcurate.operators import dedup as dd
from sparkcurate.operators import quality as qu
from sparkcurate.operators import rules as ru
from sparkcurate.plans import oracle_text as o
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import html_to_text, load_sources, table, to_qa_pairs

PAIRS = "pairs AS (SELECT a.conv_id, a.turn, a.text AS question, b.text AS response FROM conversations a LEFT JOIN conversations b ON b.conv_id = a.conv_id AND b.role = 'assistant' AND b.turn = (SELECT min(c.turn) FROM conversations c WHERE c.conv_id = a.conv_id AND c.turn > a.turn) WHERE a.role = 'user')"


@query("m01_qa_pairs", f"WITH {PAIRS} SELECT conv_id, turn, CAST(length(response) AS BIGINT) AS answer_chars FROM pairs")
def m01(spark, d):
    return to_qa_pairs(table(spark, d, "conversations")).select("conv_id", "turn", F.length("response").cast("long").alias("answer_chars"))


@query("m02_sources", f"""WITH {PAIRS} SELECT 'documents' AS origin, count(*) AS n, count(text) AS answered FROM documents
UNION ALL SELECT 'conversations', count(*), count(response) FROM pairs UNION ALL SELECT 'pages', count(*), count(html) FROM pages""")
def m02(spark, d):
    return load_sources(spark, d, ("documents", "conversations", "pages")).groupBy("origin").agg(F.count(F.lit(1)).alias("n"), F.count("response").alias("answered"))


@query("m03_lang_filter", "SELECT doc_id FROM documents WHERE lang = 'en'")
def m03(spark, d):
    return ru.filter_language(table(spark, d, "documents")).select("doc_id")


_STOPS = {k: "[" + ", ".join(f"'{w}'" for w in v) + "]" for k, v in ru.STOP_WORDS.items()}


@query("m03b_lang_detect", f"""WITH h AS (SELECT doc_id, {', '.join(f"len(list_intersect(list_distinct({o.tok('text')}), {v})) AS {k}" for k, v in _STOPS.items())} FROM documents)
SELECT doc_id, CASE greatest(en, fr, de, es) WHEN 0 THEN NULL WHEN en THEN 'en' WHEN fr THEN 'fr' WHEN de THEN 'de' ELSE 'es' END AS detected FROM h""")
def m03b(spark, d):
    return table(spark, d, "documents").select("doc_id", ru.detect_language(F.col("text")).alias("detected"))


@query("m04_complete", f"SELECT doc_id FROM documents WHERE len({o.tok('text')}) >= 5 AND regexp_matches(trim(text), '[.!?]$')")
def m04(spark, d):
    return ru.filter_complete(table(spark, d, "documents")).select("doc_id")


@query("m05_missing_traces", f"WITH {PAIRS} SELECT conv_id, turn FROM pairs WHERE response IS NULL")
def m05(spark, d):
    return ru.missing_traces(to_qa_pairs(table(spark, d, "conversations"))).select("conv_id", "turn")


@query("m06_distill", f"WITH {PAIRS} SELECT conv_id, turn, coalesce(response, 'stub:' || md5(conv_id || '-' || turn || ':1')) AS response FROM pairs")
def m06(spark, d):
    return qu.distill(to_qa_pairs(table(spark, d, "conversations")), qu.StubClient()).select("conv_id", "turn", "response")


@query("m07_domain", f"SELECT {o.DOMAIN} AS domain, source AS category, count(*) AS n FROM documents GROUP BY ALL")
def m07(spark, d):
    return ru.annotate_domain(table(spark, d, "documents")).groupBy("domain", "category").agg(F.count(F.lit(1)).alias("n"))


@query("m07b_taxonomy", f"""SELECT domain, CASE WHEN domain = 'science' THEN domain ELSE domain || '-' || source END AS category, count(*) AS n
FROM (SELECT source, {o.DOMAIN} AS domain FROM documents) GROUP BY ALL""")
def m07b(spark, d):
    docs = table(spark, d, "documents")
    # the taxonomy is one row a source; science stays flat
    taxonomy = docs.select("source").distinct().select("source", domain_of_source(F.col("source")).alias("domain")).withColumn("category", F.when(F.col("domain") != "science", F.concat_ws("-", "domain", "source")))
    return ru.annotate_taxonomy(docs, taxonomy).groupBy("domain", "category").agg(F.count(F.lit(1)).alias("n"))


@query("m09_encode")
def m09(spark, d):
    return cl.encode(table(spark, d, "documents"), "doc_id", "text").select("doc_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x * x), 3).alias("norm"))


_CENT = "c AS (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS cluster, embedding AS center FROM (SELECT * FROM embeddings ORDER BY vec_id LIMIT 8))"
_ASSIGN = f"""{_CENT}, dist AS (SELECT vec_id, cluster, list_sum(list_transform(list_zip(embedding, center), lambda p: (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)) * (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)))) AS d FROM embeddings, c),
a AS (SELECT vec_id, CAST(cluster AS INTEGER) AS cluster, d FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY d, cluster) AS k FROM dist) WHERE k = 1)"""


def _centroids(vectors: DataFrame, k: int = 8) -> DataFrame:
    rows = vectors.orderBy("vec_id").limit(k).collect()
    return vectors.sparkSession.createDataFrame([(i, [float(x) for x in r["embedding"]]) for i, r in enumerate(rows)], "cluster int, center array<double>")


@query("m10_kmeans")
def m10(spark, d):
    found, _ = cl.cluster(table(spark, d, "embeddings"), "vec_id", 8)
    return found.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("dist"), 6).alias("mean_dist"))


@query("m10_bisecting")
def m10_bisecting(spark, d):
    found, _ = cl.cluster(table(spark, d, "embeddings"), "vec_id", 8, algo="bisecting")
    return found.groupBy("cluster").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("dist"), 6).alias("mean_dist"))


@query("m10b_assign", f"WITH {_ASSIGN} SELECT vec_id, cluster, round(d, 6) AS dist FROM a")
def m10b(spark, d):
    vectors = table(spark, d, "embeddings")
    return cl.assign_batched(vectors, _centroids(vectors), "vec_id").select("vec_id", "cluster", F.round("dist", 6).alias("dist"))


@query("m10b_assign_expression", f"WITH {_ASSIGN} SELECT vec_id, cluster, round(d, 6) AS dist FROM a")
def m10b_expression(spark, d):
    vectors = table(spark, d, "embeddings")
    return cl.assign(vectors, _centroids(vectors), "vec_id").select("vec_id", "cluster", F.round("dist", 6).alias("dist"))


@query("m10c_lloyd_step", f"""WITH {_ASSIGN}, e AS (SELECT vec_id, unnest(embedding) AS x, unnest(generate_series(0, len(embedding) - 1)) AS dim FROM embeddings)
SELECT cluster, CAST(dim AS INTEGER) AS dim, round(avg(CAST(x AS DOUBLE)), 6) AS value FROM e JOIN a USING (vec_id) GROUP BY ALL""")
def m10c(spark, d):
    vectors = table(spark, d, "embeddings")
    return cl.lloyd_step(vectors, cl.assign_batched(vectors, _centroids(vectors), "vec_id"), "vec_id").select("cluster", "dim", F.round("value", 6).alias("value"))


@query("m10d_hierarchical")
def m10d(spark, d):
    return cl.cluster_hierarchical(table(spark, d, "embeddings"), "vec_id", 4, 4).groupBy("cluster").agg(F.count(F.lit(1)).alias("n"))


@query("m13_containment", f"""WITH {o.grams('g', 'documents', 'doc_id', 20)}, s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL),
hit AS (SELECT a, b FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8)
SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT b FROM hit)""")
def m13(spark, d):
    return dd.drop_contained(table(spark, d, "documents").select("doc_id", "text"), "doc_id", "text").select("doc_id")


@query("m13_longest", f"""WITH {o.grams('g', 'documents', 'doc_id', 20)}, s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL),
hit AS (SELECT a, b FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8)
SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT CASE WHEN db.n_chars > da.n_chars THEN a ELSE b END FROM hit JOIN documents da ON da.doc_id = a JOIN documents db ON db.doc_id = b)""")
def m13_longest(spark, d):
    return dd.drop_contained(table(spark, d, "documents").select("doc_id", "text", "n_chars"), "doc_id", "text", priority="n_chars").select("doc_id")


@query("m13a_any", f"WITH {o.grams('g', 'documents', 'doc_id', 20)}, f AS (SELECT gram, min(doc_id) AS m FROM g GROUP BY gram) SELECT DISTINCT doc_id FROM g JOIN f USING (gram) WHERE doc_id > m")
def m13a(spark, d):
    return dd.shares_any(table(spark, d, "documents"), "doc_id", "text")


@query("m13b_template", f"""WITH {o.grams('g0', 'documents', 'doc_id', 20)}, c AS (SELECT gram FROM g0 GROUP BY gram HAVING count(*) > 5), g AS (SELECT * FROM g0 WHERE gram NOT IN (SELECT gram FROM c)),
s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id), p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL)
SELECT a, b, shared, round(shared / least(sa.n, sb.n), 6) AS containment FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8""")
def m13b(spark, d):
    return dd.overlap_pairs(table(spark, d, "documents"), "doc_id", "text", max_df=5).select("a", "b", "shared", F.round("containment", 6).alias("containment"))


@query("m13c_exact", "SELECT doc_id, doc_id = min(doc_id) OVER (PARTITION BY text) AS kept FROM documents")
def m13c(spark, d):
    return dd.dedup_exact(table(spark, d, "documents"), "doc_id", "text")


@query("m13d_groups", f"""WITH RECURSIVE {o.grams('g', 'documents', 'doc_id', 20)}, s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL),
hit AS (SELECT a, b FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8),
e AS (SELECT a, b FROM hit UNION SELECT b, a FROM hit),
r(doc_id, reach) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, e.b FROM r JOIN e ON r.reach = e.a)
SELECT doc_id, min(reach) AS grp FROM r GROUP BY doc_id""")
def m13d(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "text")
    return dd.duplicate_groups(docs, "doc_id", dd.overlap_pairs(docs, "doc_id", "text"))


@query("m13e_minhash", f"""WITH {o.grams('g', 'documents', 'doc_id', 20)}, s AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY ALL)
SELECT a, b, shared, round(shared / least(sa.n, sb.n), 6) AS containment FROM p JOIN s sa ON sa.doc_id = a JOIN s sb ON sb.doc_id = b WHERE shared / least(sa.n, sb.n) >= 0.8""")
def m13e(spark, d):
    return dd.dedup_minhash(table(spark, d, "documents"), "doc_id", "text").select("a", "b", "shared", F.round("containment", 6).alias("containment"))


_BOXED = "strpos(text, chr(92) || 'boxed{') > 0"


@query("m15_format", rf"""SELECT doc_id, array_to_string(list_filter([CASE WHEN trim(text) = '' THEN 'empty' END, CASE WHEN NOT regexp_matches(text, '[.!?}}`]\s*$') THEN 'incomplete' END,
CASE WHEN len({o.tok('text')}) > 2000 THEN 'too_long' END, CASE WHEN domain = 'math' AND NOT {_BOXED} THEN 'no_boxed_answer' END, CASE WHEN domain = 'code' AND strpos(text, '```') = 0 THEN 'no_program' END], lambda x: x IS NOT NULL), ',') AS reasons
FROM (SELECT *, {o.DOMAIN} AS domain FROM documents)""")
def m15(spark, d):
    docs = table(spark, d, "documents")
    return docs.select("doc_id", F.concat_ws(",", ru.format_reasons(F.col("text"), domain_of_source(F.col("source")), 2000)).alias("reasons"))


@query("m16_verify_boxed", "SELECT doc_id, doc_id % 2 = 0 AS passed FROM documents")
def m16(spark, d):
    # a right boxed fraction for even ids, a wrong one for odd ids
    docs = table(spark, d, "documents").select("doc_id", F.concat(F.lit("so \\boxed{\\frac{"), (F.col("doc_id") * 2 + F.col("doc_id") % 2).cast("string"), F.lit("}{2}}")).alias("response"), F.col("doc_id").cast("string").alias("truth"))
    return qu.verify_boxed(docs).select("doc_id", "passed")


_RETRY = """WITH t AS (SELECT doc_id, a FROM documents, (SELECT unnest(generate_series(1, 8)) AS a) WHERE CAST('0x' || substr(md5(doc_id || ':' || a), 1, 1) AS INTEGER) < 5)
SELECT doc_id, CAST(coalesce(min(a), 8) AS INTEGER) AS attempts, min(a) IS NOT NULL AS passed FROM documents LEFT JOIN t USING (doc_id) GROUP BY doc_id"""


@query("m17_retry", _RETRY)
def m17(spark, d):
    return qu.verify_regenerate_stub(table(spark, d, "documents"), "doc_id")


@query("m17_retry_in_batch", _RETRY)
def m17_batch(spark, d):
    def verdict(ids, responses, attempt):
        return [int(hashlib.md5(f"{i}:{attempt}".encode()).hexdigest()[0], 16) < 5 for i in ids]

    records = table(spark, d, "documents").select("doc_id", F.lit("").alias("question"), F.lit("").alias("response"))
    return qu.verify_regenerate(records, "doc_id", qu.StubClient(), verdict).select("doc_id", "attempts", "passed")


@query("m17b_retry_rounds", _RETRY)
def m17b(spark, d):
    return qu.verify_regenerate_rounds(table(spark, d, "documents"), "doc_id")


_HEUR = rf"""SELECT doc_id, source, CASE WHEN len(t) > 0 THEN round(len(list_distinct(t)) / len(t), 6) ELSE 0.0 END AS variety, round(1 - len(list_distinct(l)) / len(l), 6) AS repeated_lines,
CASE WHEN length(text) > 0 THEN round(length(regexp_replace(text, '[\p{{L}}\p{{N}}\s]', '', 'g')) / length(text), 6) ELSE 0.0 END AS signs FROM (SELECT *, {o.tok('text')} AS t, string_split(text, chr(10)) AS l FROM documents)"""


@query("m18_heuristics", f"SELECT doc_id, variety, repeated_lines, signs FROM ({_HEUR})")
def m18(spark, d):
    docs = table(spark, d, "documents")
    return docs.select("doc_id", *[c.alias(n) for n, c in ru.heuristic_scores(F.col("text")).items()])


@query("m18_judge_filter", f"SELECT doc_id FROM ({_HEUR}) WHERE variety >= 0.3 AND repeated_lines <= 0.3 AND signs <= 0.15")
def m18_filter(spark, d):
    return ru.filter_judged(table(spark, d, "documents")).select("doc_id")


@query("m18b_quality_model")
def m18b(spark, d):
    from sparkcurate.operators.judge import quality_scores

    return quality_scores(table(spark, d, "documents"), table(spark, d, "labels"))


@query("m19_route", f"SELECT CASE WHEN {o.DOMAIN} = 'science' THEN 'judge' ELSE 'verify' END AS route, count(*) AS n FROM documents GROUP BY ALL")
def m19(spark, d):
    return qu.route(ru.annotate_domain(table(spark, d, "documents"))).groupBy("route").agg(F.count(F.lit(1)).alias("n"))


_BG = o.grams("bg", "benchmark", "item_id", 15)
_DG = o.grams("dg", "documents", "doc_id", 15)
_ANY = f"{_BG}, {_DG}, hit AS (SELECT DISTINCT doc_id FROM dg WHERE gram IN (SELECT gram FROM bg))"


@query("m20_decontam_any", f"WITH {_ANY} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM hit)")
def m20(spark, d):
    return de.decontaminate_ngrams(table(spark, d, "documents"), table(spark, d, "benchmark"), "doc_id").select("doc_id")


_SHARE = f"""{_BG}, {_DG}, z AS (SELECT item_id, count(*) AS size FROM bg GROUP BY item_id),
sh AS (SELECT doc_id, max(share) AS share FROM (SELECT doc_id, item_id, count(*) / max(size) AS share FROM dg JOIN bg USING (gram) JOIN z USING (item_id) GROUP BY ALL) GROUP BY doc_id)"""


@query("m20b_share", f"WITH {_SHARE} SELECT doc_id, round(share, 6) AS share FROM sh")
def m20b(spark, d):
    return de.contaminated_share(table(spark, d, "documents"), table(spark, d, "benchmark"), "doc_id").select("doc_id", F.round("share", 6).alias("share"))


@query("m20b_decontam_share", f"WITH {_SHARE} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM sh WHERE share >= 0.5)")
def m20b_filter(spark, d):
    return de.decontaminate_ngrams(table(spark, d, "documents"), table(spark, d, "benchmark"), "doc_id", rule="containment").select("doc_id")


# plants: every tenth vector is an item of the benchmark side
_COS = """c AS (SELECT a.vec_id, max(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[]))) AS cosine FROM embeddings a, (SELECT embedding FROM embeddings WHERE vec_id % 10 = 0) b GROUP BY a.vec_id)"""


def _planted(spark, d):
    vectors = table(spark, d, "embeddings")
    return vectors, vectors.filter(F.col("vec_id") % 10 == 0).select("embedding")


@query("m21_max_cosine", f"WITH {_COS} SELECT vec_id, round(cosine, 6) AS cosine FROM c")
def m21(spark, d):
    return de.max_cosine(*_planted(spark, d), "vec_id").select("vec_id", F.round("cosine", 6).alias("cosine"))


@query("m21_cosine", f"WITH {_COS} SELECT vec_id FROM c WHERE cosine <= 0.9")
def m21_filter(spark, d):
    return de.decontaminate_cosine(*_planted(spark, d), "vec_id").select("vec_id")


@query("m21b_chunked_cosine")
def m21b(spark, d):
    from sparkcurate.operators.semantic import chunked_contamination

    return chunked_contamination(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query("m22_combined", f"WITH {_ANY}, {_COS}, j AS (SELECT doc_id, coalesce(cosine, -1) > 0.9 AS semantic, doc_id IN (SELECT doc_id FROM hit) AS lexical FROM documents LEFT JOIN c ON c.vec_id = documents.doc_id) SELECT doc_id, lexical, semantic FROM j WHERE lexical OR semantic")
def m22(spark, d):
    """Rejected ids with the rule that rejects them; the vectors are keyed by position here, to have planted ones."""
    from sparkcurate.operators.semantic import combine_rejections

    vectors, items = _planted(spark, d)
    docs = table(spark, d, "documents")
    lexical = de.contaminated_any(docs, table(spark, d, "benchmark"), "doc_id")
    semantic = de.max_cosine(vectors.withColumnRenamed("vec_id", "doc_id"), items, "doc_id").filter("cosine > 0.9").select("doc_id").join(docs.select("doc_id"), "doc_id", "left_semi")
    return combine_rejections(lexical, semantic, "doc_id")


@query("m22b_strict_pool")
def m22b(spark, d):
    from sparkcurate.operators.semantic import strict_pool

    return strict_pool(table(spark, d, "documents"))


@query("w13_pages", r"""SELECT page_id, CAST(length(trim(regexp_replace(replace(replace(replace(replace(replace(replace(
regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', chr(39)), '&amp;', '&'), '[ \t\r\n]+', ' ', 'g'))) AS BIGINT) AS chars FROM pages""")
def w13(spark, d):
    return table(spark, d, "pages").select("page_id", F.length(html_to_text(F.col("html"))).cast("long").alias("chars"))
