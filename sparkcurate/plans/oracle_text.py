"""Shared DuckDB fragments of the oracles."""

TOK = r"list_filter(string_split_regex(lower(coalesce({0}, '')), '[^\p{{L}}\p{{N}}]+'), lambda w: w <> '')"


def tok(column: str) -> str:
    return TOK.format(column)


DOMAIN = r"CASE CAST(regexp_extract(source, '(\d+)$', 1) AS INTEGER) % 3 WHEN 0 THEN 'math' WHEN 1 THEN 'code' ELSE 'science' END"
QUESTION = r"regexp_extract(text, '^([^.!?\n]+[.!?]?)', 1)"
RND = "md5(concat_ws(':', '42', CAST(doc_id AS VARCHAR)))"


def grams(name: str, source: str, key: str, n: int) -> str:
    """CTE of distinct (key, gram)."""
    return f"""{name} AS (SELECT DISTINCT {key}, array_to_string(t[s : s + {n - 1}], ' ') AS gram FROM (
      SELECT {key}, t, unnest(generate_series(1, len(t) - {n - 1})) AS s FROM (SELECT {key}, {tok('text')} AS t FROM {source}) WHERE len(t) >= {n}))"""


def balanced(source: str, group: str, order: str, budget: int | str, key: str = "doc_id") -> str:
    return f"SELECT {key} FROM (SELECT {key}, {group} AS g, row_number() OVER (PARTITION BY {group} ORDER BY {order}) AS rn FROM {source}) ORDER BY rn, g LIMIT {budget}"


def dual(source: str, order: str, budget: int | str) -> str:
    """Both draws merged and topped up from the category draw of the rest; the budget is a number or a scalar query."""
    half = f"{budget} // 2"
    return f"""(WITH a AS ({balanced(source, 'category', order, f'({half})')}), b AS ({balanced(source, 'cluster', order, f'({budget} - {half})')}),
      m AS (SELECT doc_id FROM a UNION SELECT doc_id FROM b),
      rest AS (SELECT doc_id, category AS g, row_number() OVER (PARTITION BY category ORDER BY {order}) AS rn FROM {source} WHERE doc_id NOT IN (SELECT doc_id FROM m)),
      more AS (SELECT doc_id, row_number() OVER (ORDER BY rn, g) AS k FROM rest)
      SELECT doc_id FROM m UNION ALL SELECT doc_id FROM more WHERE k <= {budget} - (SELECT count(*) FROM m))"""


def vectors(source: str, key: str, size: int) -> str:
    """CTE vec_<source> of (key, v, n): signed sums of the tokens' digests over so many buckets, and their square."""
    signed = f"list_transform({tok('text')}, lambda w: {{'slot': CAST('0x' || substr(md5(w), 1, 7) AS BIGINT) % {size}, 'sign': CASE WHEN CAST('0x' || substr(md5(w), 8, 1) AS BIGINT) % 2 = 0 THEN 1 ELSE -1 END}})"
    one = "coalesce(list_sum(list_transform(list_filter(h, lambda x: x.slot = i), lambda x: x.sign)), 0)"
    return f"""vec_{source} AS MATERIALIZED (SELECT {key}, v, list_sum(list_transform(v, lambda x: x * x)) AS n FROM (SELECT {key}, list_transform(generate_series(0, {size - 1}), lambda i: {one}) AS v FROM (SELECT {key}, {signed} AS h FROM {source})))"""


_V = """v AS (SELECT doc_id, list_transform(generate_series(0, 15), lambda i: list_sum(list_transform(list_filter(h, lambda x: x.slot = i), lambda x: x.sign))) AS v FROM (
  SELECT doc_id, list_transform(t, lambda w: {'slot': CAST('0x' || substr(md5(w), 1, 7) AS BIGINT) %% 16, 'sign': CASE WHEN CAST('0x' || substr(md5(w), 8, 1) AS BIGINT) %% 2 = 0 THEN 1 ELSE -1 END}) AS h
  FROM (SELECT doc_id, %s AS t FROM documents)))""" % tok("text")

SCORED = f"""rec AS (SELECT doc_id, text, {DOMAIN} AS domain, source AS category, n_chars, {QUESTION} AS question, {tok('text')} AS t, {tok(QUESTION)} AS q FROM documents),
ent AS (SELECT doc_id, round(log2(sum(c)) - sum(c * log2(c)) / sum(c), 6) AS complexity FROM (SELECT doc_id, w, count(*) AS c FROM (SELECT doc_id, unnest(q) AS w FROM rec) GROUP BY ALL) GROUP BY doc_id),
aw AS (SELECT doc_id, w, count(*) AS n FROM (SELECT doc_id, unnest(t) AS w FROM rec) GROUP BY ALL),
qw AS (SELECT doc_id, w, count(*) AS m FROM (SELECT doc_id, unnest(q) AS w FROM rec) GROUP BY ALL),
cw AS (SELECT w, sum(n) AS c FROM aw GROUP BY w), tot AS (SELECT sum(c) AS total, count(*) AS kinds FROM cw),
price AS (SELECT aw.doc_id, aw.n, (c + 1) / (total + kinds) AS alone, coalesce(m, 0) AS m, len(rec.q) AS nq FROM aw JOIN cw USING (w) JOIN rec ON rec.doc_id = aw.doc_id CROSS JOIN tot LEFT JOIN qw ON qw.doc_id = aw.doc_id AND qw.w = aw.w),
ifd AS (SELECT doc_id, round(sum(n * ln(CASE WHEN nq > 0 THEN 0.5 * alone + 0.5 * m / nq ELSE alone END)) / sum(n * ln(alone)), 6) AS ifd FROM price GROUP BY doc_id),
{_V},
vv AS (SELECT doc_id, list_transform(v, lambda x: coalesce(x, 0)) AS v FROM v),
heads AS (SELECT row_number() OVER (ORDER BY doc_id) - 1 AS cluster, v AS c FROM (SELECT * FROM vv WHERE list_sum(list_transform(v, lambda x: x * x)) > 0 ORDER BY doc_id LIMIT 8)),
near AS (SELECT doc_id, cluster, CAST(list_sum(list_transform(list_zip(v, c), lambda p: p[1] * p[2])) AS DOUBLE) / sqrt(CAST(list_sum(list_transform(c, lambda x: x * x)) AS DOUBLE)) AS s FROM vv, heads),
clu AS (SELECT doc_id, CAST(cluster AS INTEGER) AS cluster FROM (SELECT doc_id, cluster, row_number() OVER (PARTITION BY doc_id ORDER BY s DESC, cluster) AS k FROM near) WHERE k = 1),
scored AS MATERIALIZED (SELECT rec.doc_id, domain, category, n_chars, len(t) AS n_tokens, coalesce(complexity, 0) AS complexity, coalesce(ifd, 0) AS ifd, cluster, md5(concat_ws(':', '42', CAST(rec.doc_id AS VARCHAR))) AS rnd
  FROM rec LEFT JOIN ent USING (doc_id) LEFT JOIN ifd USING (doc_id) JOIN clu USING (doc_id))"""

STRATEGY = {
    "random": "(SELECT doc_id FROM scored ORDER BY rnd, doc_id LIMIT {b})",
    "dual": lambda b, src="scored": dual(src, "rnd, doc_id", b),
    "length": "(SELECT doc_id FROM scored ORDER BY n_chars DESC, doc_id LIMIT {b})",
    "complexity+dual": lambda b, src="scored": dual(src, "complexity DESC, doc_id", b),
    "ifd+dual": lambda b, src="scored": dual(src, "ifd DESC, doc_id", b),
    "length+embedding": lambda b, src="scored": f"({balanced(src, 'cluster', 'n_chars DESC, doc_id', b)})",
    "length+category": lambda b, src="scored": f"({balanced(src, 'category', 'n_chars DESC, doc_id', b)})",
    "length+dual": lambda b, src="scored": dual(src, "n_chars DESC, doc_id", b),
}


def strategy(name: str, budget: int) -> str:
    law = STRATEGY[name]
    return law.format(b=budget) if isinstance(law, str) else law(budget)
