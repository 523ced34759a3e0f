"""The relational surface around the methods, one query an operator."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from sparkcurate.operators.relational import as_of, range_join, salted_join
from sparkcurate.plans.registry import query
from sparkcurate.sources.tables import table


@query("op_pricing_summary", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS discount, count(*) AS n FROM lineitem GROUP BY ALL")
def pricing(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"), F.round(F.avg("l_discount"), 6).alias("discount"), F.count(F.lit(1)).alias("n"))


@query("op_join_inner", "SELECT n_name, r_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def join_inner(spark, d):
    nation = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name", "r_name").agg(F.count(F.lit(1)).alias("customers"))


@query("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def join_left(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("op_join_full", "SELECT coalesce(c_nationkey, s_nationkey) AS nation, count(DISTINCT c_custkey) AS customers, count(DISTINCT s_suppkey) AS suppliers FROM customer FULL JOIN supplier ON c_nationkey = s_nationkey GROUP BY 1")
def join_full(spark, d):
    # counted before the join: no product of customers and suppliers
    c = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("c"))
    s = table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("s"))
    return c.join(s, "nation", "full").select("nation", F.coalesce("c", F.lit(0)).alias("customers"), F.coalesce("s", F.lit(0)).alias("suppliers"))


@query("op_join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def join_semi(spark, d):
    rich = table(spark, d, "orders").filter("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, d, "customer").join(rich, "c_custkey", "left_semi").select("c_custkey")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey")


@query("op_join_salted", "SELECT p_brand, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def join_salted(spark, d):
    left = table(spark, d, "lineitem").select(F.col("l_partkey").alias("key"), "l_extendedprice", "l_orderkey", "l_linenumber")
    return salted_join(left, table(spark, d, "part").select(F.col("p_partkey").alias("key"), "p_brand"), "key").groupBy("p_brand").agg(F.round(F.sum("l_extendedprice"), 2).alias("total"))


_BANDS = [(0, 500, "short"), (500, 2000, "medium"), (2000, 1_000_000, "long")]


@query("op_join_range", "SELECT name, count(*) AS n FROM documents JOIN (VALUES (0, 500, 'short'), (500, 2000, 'medium'), (2000, 1000000, 'long')) b(lo, hi, name) ON n_chars >= lo AND n_chars < hi GROUP BY name")
def join_range(spark, d):
    bands = spark.createDataFrame(_BANDS, "lo long, hi long, name string")
    return range_join(table(spark, d, "documents").select("n_chars"), bands, "n_chars", "lo", "hi", 1000).groupBy("name").agg(F.count(F.lit(1)).alias("n"))


@query("op_join_asof", "SELECT e.event_id, (SELECT b.value FROM events b WHERE b.user_id = e.user_id AND b.event_type = 'purchase' AND b.ts <= e.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) IS NOT NULL AS bought_before FROM events e WHERE e.event_type = 'click'")
def join_asof(spark, d):
    events = table(spark, d, "events")
    found = as_of(events.filter("event_type = 'click'").select("event_id", "user_id", "ts"), events.filter("event_type = 'purchase'").select("user_id", "ts", "value"), "user_id", "ts", "value")
    return found.select("event_id", F.col("last_value").isNotNull().alias("bought_before"))


@query("op_lateral", "SELECT doc_id, i AS line, length(l) AS chars FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l, unnest(generate_series(1, len(string_split(text, chr(10))))) AS i FROM documents)")
def lateral(spark, d):
    return table(spark, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("i", "l")).select("doc_id", (F.col("i") + 1).cast("long").alias("line"), F.length("l").cast("long").alias("chars"))


@query("op_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n, grouping_id(l_returnflag, l_linestatus) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def rollup(spark, d):
    return table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("op_cube", "SELECT lang, source, count(*) AS n, grouping_id(lang, source) AS level FROM documents GROUP BY CUBE (lang, source)")
def cube(spark, d):
    return table(spark, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("op_pivot", "SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'fr') AS fr, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'es') AS es FROM documents GROUP BY source")
def pivot(spark, d):
    return table(spark, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).count().na.fill(0)


@query("op_unpivot", "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot(spark, d):
    return table(spark, d, "labels").unpivot(["doc_id"], ["quality", "toxic"], "label", "value")


@query("op_windows", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, lag(o_orderkey) OVER w AS prev, lead(o_orderkey) OVER w AS nxt, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS run FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def windows(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, d, "orders").select(
        "o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"),
        F.lag("o_orderkey").over(w).alias("prev"), F.lead("o_orderkey").over(w).alias("nxt"), F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("run"),
    )


@query("op_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("op_set_union", "SELECT n_nationkey AS k FROM nation UNION SELECT r_regionkey FROM region")
def set_union(spark, d):
    return table(spark, d, "nation").select(F.col("n_nationkey").alias("k")).union(table(spark, d, "region").select("r_regionkey")).distinct()


@query("op_set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def set_intersect(spark, d):
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(spark, d, "supplier").select("s_nationkey"))


@query("op_set_except_all", "SELECT o_custkey AS k FROM orders EXCEPT ALL SELECT c_custkey FROM customer")
def set_except(spark, d):
    return table(spark, d, "orders").select(F.col("o_custkey").alias("k")).exceptAll(table(spark, d, "customer").select("c_custkey"))


@query("op_sample_hash", "SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(concat_ws(':', '42', CAST(doc_id AS VARCHAR))), 1, 7) AS BIGINT) < 26843545")
def sample_hash(spark, d):
    from sparkcurate.functions.text import hex_number, seeded

    return table(spark, d, "documents").filter(hex_number(seeded("doc_id"), 1, 7) < 26843545).select("doc_id")


@query("op_strings", r"SELECT doc_id, length(trim(text)) AS trimmed, lower(substr(text, 1, 5)) AS head, regexp_extract(text, '([a-z]+)', 1) AS word, length(regexp_replace(text, '[aeiou]', '', 'g')) AS bare, md5(text) AS digest, sha256(text) AS sha, len(string_split(text, ' ')) AS parts FROM documents")
def strings(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.length(F.trim(t)).cast("long").alias("trimmed"), F.lower(F.substring(t, 1, 5)).alias("head"), F.regexp_extract(t, "([a-z]+)", 1).alias("word"), F.length(F.regexp_replace(t, "[aeiou]", "")).cast("long").alias("bare"), F.md5(t).alias("digest"), F.sha2(t, 256).alias("sha"), F.size(F.split(t, " ")).cast("long").alias("parts"))


@query("op_dates", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, count(*) AS n, max(date_diff('day', CAST(date_trunc('month', o_orderdate) AS DATE), CAST(o_orderdate AS DATE))) AS last_day FROM orders GROUP BY 1")
def dates(spark, d):
    month = F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))
    return table(spark, d, "orders").select(month.alias("m"), F.datediff("o_orderdate", month).alias("k")).groupBy(F.date_format("m", "yyyy-MM-dd").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max("k").cast("long").alias("last_day"))


@query("op_math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(sqrt(l_quantity), 6) AS b, round(pow(l_discount, 2), 6) AS c, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l FROM lineitem")
def math(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.log("l_extendedprice"), 6).alias("a"), F.round(F.sqrt("l_quantity"), 6).alias("b"), F.round(F.pow("l_discount", F.lit(2)), 6).alias("c"), F.greatest("l_discount", "l_tax").alias("g"), F.least("l_discount", "l_tax").alias("l"))


@query("op_arrays", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_sum(list_transform(embedding[1:8], lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS head, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top FROM embeddings")
def arrays(spark, d):
    e = F.col("embedding").cast("array<double>")
    return table(spark, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda s, x: s + x * x), 6).alias("head"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"))


@query("op_maps", "SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(DISTINCT lang) AS kinds FROM documents GROUP BY source")
def maps(spark, d):
    per = table(spark, d, "documents").groupBy("source", "lang").agg(F.count(F.lit(1)).alias("n")).groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return per.select("source", F.coalesce(F.try_element_at("m", F.lit("en")), F.lit(0)).alias("en"), F.size("m").cast("long").alias("kinds"))


@query("op_json", "SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def json(spark, d):
    return table(spark, d, "events").select(F.from_json("props", "k int").alias("p")).groupBy(F.col("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("op_distinct_exact", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def distinct_exact(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("op_distinct_sketch", "SELECT event_type, count(DISTINCT user_id) AS users, true AS near, true AS hll_near FROM events GROUP BY event_type")
def distinct_sketch(spark, d):
    """Both sketches lie within four of their standard errors of the exact count."""
    per = table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(14))).alias("b"))
    near = lambda c, error: F.abs(F.col(c) - F.col("users")) <= 4 * error * F.col("users") + 1
    return per.select("event_type", "users", near("a", 0.02).alias("near"), near("b", 0.0065).alias("hll_near"))


@query("op_aggregates", "SELECT o_orderpriority, arg_max(o_orderkey, o_totalprice) AS top, arg_min(o_orderkey, o_totalprice) AS low, bool_or(o_totalprice > 400000) AS any_rich, round(stddev_samp(o_totalprice), 4) AS sd, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
def aggregates(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").agg(F.max_by("o_orderkey", "o_totalprice").alias("top"), F.min_by("o_orderkey", "o_totalprice").alias("low"), F.bool_or(F.col("o_totalprice") > 400000).alias("any_rich"), F.round(F.stddev_samp("o_totalprice"), 4).alias("sd"), F.count(F.when(F.col("o_orderstatus") == "F", 1)).alias("done"), F.round(F.percentile("o_totalprice", F.lit(0.9)), 4).alias("p90"))


@query("op_null_safe", "SELECT count(*) AS n FROM labels a JOIN labels b ON a.doc_id = b.doc_id AND nullif(a.toxic, 0) IS NOT DISTINCT FROM nullif(b.toxic, 0)")
def null_safe(spark, d):
    labels = table(spark, d, "labels").select("doc_id", F.nullif("toxic", F.lit(0)).alias("t"))
    a, b = labels.alias("a"), labels.alias("b")
    return a.join(b, (F.col("a.doc_id") == F.col("b.doc_id")) & F.col("a.t").eqNullSafe(F.col("b.t"))).agg(F.count(F.lit(1)).alias("n"))


@query("op_vector_mean", "SELECT label, CAST(i AS INTEGER) AS dim, round(avg(CAST(x AS DOUBLE)), 6) AS value FROM (SELECT label, unnest(embedding) AS x, unnest(generate_series(0, 63)) AS i FROM embeddings) GROUP BY ALL")
def vector_mean(spark, d):
    return table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("dim", "x")).groupBy("label", "dim").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("value"))


@query("op_sql_surface", "SELECT doc_id, count(*) AS grams FROM (SELECT doc_id, unnest(generate_series(1, len(t) - 2)) FROM (SELECT doc_id, list_filter(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+'), lambda w: w <> '') AS t FROM documents) WHERE len(t) >= 3) GROUP BY doc_id")
def sql_surface(spark, d):
    """The registered table function ngrams(text, n) in SQL."""
    from sparkcurate.functions.sql import register

    register(spark)
    docs = table(spark, d, "documents")
    return spark.sql("SELECT doc_id, count(*) AS grams FROM {docs}, LATERAL ngrams(text, 3) GROUP BY doc_id", docs=docs)
