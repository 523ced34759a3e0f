"""DuckDB SQL for the operators that SQL can express, written apart from the Spark plans."""

from __future__ import annotations

from sparkcurate.llm.licenses import INDEXED_WORDS, TEMPLATES

_WORDS = r"list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '')"

DECONTAMINATION = f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_WORDS} AS w FROM benchmark),
bw AS (
  SELECT item, least(13, len(w)) AS n, unnest(generate_series(1, len(w) - least(13, len(w)) + 1)) AS s, w FROM b WHERE len(w) > 0),
spans AS (SELECT DISTINCT item, n, array_to_string(w[s : s + n - 1], ' ') AS span FROM bw),
sizes AS (SELECT DISTINCT n FROM spans),
dw AS (SELECT rid, n, unnest(generate_series(1, len(w) - n + 1)) AS s, w FROM d, sizes WHERE len(w) >= n),
hits AS (SELECT rid, dw.s, dw.n, item FROM dw JOIN spans ON spans.n = dw.n AND spans.span = array_to_string(dw.w[dw.s : dw.s + dw.n - 1], ' ')),
covered AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(generate_series(s, s + n - 1)) AS p FROM hits) GROUP BY rid),
items AS (SELECT rid, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS listed FROM hits GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(listed, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN covered USING (rid) LEFT JOIN items USING (rid)
"""


def _jump(shards: int) -> str:
    """The jump walk as a recursive query over distinct keys."""
    return f"""
walk{shards} AS (
  SELECT key, CAST(CASE WHEN key < 0 THEN key + 18446744073709551616 ELSE key END AS HUGEINT) AS k, CAST(-1 AS BIGINT) AS b, CAST(0 AS BIGINT) AS j FROM keys
  UNION ALL
  SELECT key, nk, j, CAST(floor((j + 1) * (2147483648.0::DOUBLE / CAST(nk // 8589934592 + 1 AS DOUBLE))) AS BIGINT)
  FROM (SELECT key, j, (k * 2862933555777941757 + 1) % 18446744073709551616 AS nk FROM walk{shards} WHERE j < {shards})),
shards{shards} AS (SELECT key, CAST(max(j) AS INTEGER) AS shard FROM walk{shards} WHERE j < {shards} GROUP BY key)"""


# CRC-32 with its usual reflected polynomial, over the bytes of the text.
_TABLE = "[" + ", ".join(str(c) for c in __import__("functools").reduce(lambda t, _: [(c >> 1) ^ (0xEDB88320 if c & 1 else 0) for c in t], range(8), list(range(256)))) + "]"

SHARDS = f"""
WITH RECURSIVE sized AS (
  SELECT row_number() OVER () AS rid, doc_id, coalesce(doc_id, 0) AS key, coalesce(text, '') AS t, strlen(coalesce(text, '')) + 1 AS size FROM documents),
texts AS (SELECT DISTINCT t FROM sized),
summed AS (
  SELECT t, xor(4294967295, list_reduce(list_transform(regexp_extract_all(hex(encode(t)), '..'), lambda h: CAST('0x' || h AS BIGINT)),
    lambda c, b: xor(c >> 8, list_extract({_TABLE}, CAST((xor(c, b) & 255) + 1 AS BIGINT))), 4294967295)) AS text_crc32 FROM texts),
keys AS (SELECT DISTINCT key FROM sized), {_jump(16)}, {_jump(17)}
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'key' AS law, s.shard,
  row_number() OVER (PARTITION BY s.shard ORDER BY doc_id NULLS FIRST, text_crc32, size) - 1 AS slot, g.shard AS grown_shard
FROM sized JOIN summed USING (t) JOIN shards16 s USING (key) JOIN shards17 g USING (key)
"""


def licenses() -> str:
    rows = [(k, t.label, t.base, o, w, t.key_offset <= o < t.key_offset + len(t.key.split())) for k, t in enumerate(TEMPLATES) for o, w in enumerate(t.words)]
    values = ", ".join(f"({k}, '{label}', {base}, {o}, '{w}', {key})" for k, label, base, o, w, key in rows)
    return f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, {_WORDS} AS w FROM documents),
tpl(k, label, base, off, word, in_key) AS (VALUES {values}),
occ AS (SELECT rid, unnest(w) AS word, unnest(generate_series(0, len(w) - 1)) AS pos FROM d WHERE len(w) > 0),
lic AS (SELECT rid, word, pos FROM occ WHERE word IN (SELECT word FROM tpl)),
df AS (SELECT word, count(DISTINCT rid) AS n FROM lic GROUP BY word),
weight AS (SELECT tpl.*, ln(((SELECT count(*) FROM d) + 1.0) / (coalesce(df.n, 0) + 1.0)) + 1.0 AS idf FROM tpl LEFT JOIN df USING (word)),
ranked AS (SELECT *, row_number() OVER (PARTITION BY k ORDER BY idf DESC, word, off) <= {INDEXED_WORDS} AS indexed FROM weight),
need AS (SELECT k, any_value(label) AS label, bool_or(base) AS base, count(*) FILTER (WHERE in_key OR indexed) AS needed, sum(idf) AS total FROM ranked GROUP BY k),
placed AS (
  SELECT rid, k, pos - off AS start, count(*) FILTER (WHERE in_key OR indexed) AS got, sum(idf) AS score
  FROM lic JOIN ranked USING (word) GROUP BY rid, k, pos - off HAVING pos - off >= 0),
good AS (SELECT rid, k, start, label, base, placed.score / total AS share FROM placed JOIN need USING (k) WHERE got = needed),
told AS (
  SELECT rid, count(*) FILTER (WHERE base) AS n_base, min(start) FILTER (WHERE base) AS first_word, max(start) FILTER (WHERE base) AS last_word,
    string_agg(DISTINCT label, ',' ORDER BY label) FILTER (WHERE base) AS base_labels, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, max(share) AS score
  FROM good GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_base, 0) AS BIGINT) AS n_base, CAST(first_word AS BIGINT) AS first_word,
  CAST(last_word AS BIGINT) AS last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels, round(coalesce(score, 0), 6) AS score
FROM d LEFT JOIN told USING (rid)
"""
