import hashlib
import re
import zlib

import pytest
from pyspark.sql import functions as F

import sparkcurate.llm.decontaminate as decontaminate_module
from sparkcurate.llm.decontaminate import decontaminate
from sparkcurate.llm.licenses import TEMPLATES, scan_licenses
from sparkcurate.llm.sharding import assign_shards

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return WORD.findall((text or "").translate(LOW))


def brute_windows(docs, items):
    windows = {}
    for item, text in items:
        w = words(text)
        n = min(13, len(w))
        for s in range(len(w) - n + 1 if w else 0):
            windows.setdefault(tuple(w[s : s + n]), set()).add(str(item))
    out = []
    for doc, text in docs:
        w, hit, found = words(text), set(), set()
        for n in {len(k) for k in windows}:
            for s in range(len(w) - n + 1):
                if m := windows.get(tuple(w[s : s + n])):
                    found |= m
                    hit |= set(range(s, s + n))
        out.append((doc, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), len(hit) > 0 and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


@pytest.fixture(params=["broadcast", "shuffle"])
def side(request, monkeypatch):
    if request.param == "shuffle":
        monkeypatch.setattr(decontaminate_module, "BROADCAST_ROWS", 0)


def test_decontamination_equals_brute_force(spark, sf, side):
    docs, items = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet")
    got = sorted((tuple(r) for r in decontaminate(docs, items).drop("__text").collect()), key=str)
    assert got == brute_windows(docs.select("doc_id", "text").collect(), items.select("item_id", "text").collect())


def test_decontamination_cases(spark, side):
    run = "a b c d e f g h i j k l m n o p"
    docs = [(1, run), (1, run), (2, None), (3, ""), (4, "zz foo bar foo bar q"), (None, "foo bar"), (1, "other text of one id"), (9, "x " * 5000 + run)]
    items = [(1, "b c d e f g h i j k l m n o"), (2, "foo bar"), (3, None), (4, "..."), (5, "foo BAR")]
    d = spark.createDataFrame(docs, "doc_id long, text string").withColumn("__w", F.lit("clash"))
    b = spark.createDataFrame(items, "item_id long, text string")
    assert sorted((tuple(r) for r in decontaminate(d, b).drop("__text").collect()), key=str) == brute_windows(docs, items)
    assert decontaminate(d.limit(0), b).count() == 0
    assert decontaminate(d, b.limit(0)).agg(F.sum("n_hit")).first()[0] == 0


def jump(key, n):
    key, b, j = key & (2**64 - 1), -1, 0
    while j < n:
        b, key = j, (key * 2862933555777941757 + 1) & (2**64 - 1)
        j = int((b + 1) * (2.0**31 / ((key >> 33) + 1)))
    return b


@pytest.mark.parametrize("rows_per_chunk", [4, 100_000])
def test_sharding(spark, rows_per_chunk):
    rows = [(i if i % 3 else 5, f"text {i % 50}") for i in range(600)] + [(-5, "é"), (None, None), (None, "q"), (7, "x"), (7, "x")]
    got = assign_shards(spark.createDataFrame(rows, "doc_id long, text string").withColumn("shard", F.lit(1)), rows_per_chunk=rows_per_chunk).toPandas()
    assert len(got) == len(rows)
    for key, shard, grown in zip(got.doc_id, got["shard"], got.grown_shard, strict=True):
        k = 0 if key != key else int(key)
        assert (shard, grown) == (jump(k, 16), jump(k, 17)) and grown in (shard, 16)
    for _, part in got.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))
    assert sorted(got.text_crc32) == sorted(zlib.crc32((t or "").encode()) for _, t in rows)
    assert assign_shards(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_licenses(spark):
    rows = [(1, "Released under the MIT License. mit  LICENSE"), (2, None), (3, ""), (4, "GNU General-Public, License; apache license version 2.0"), (4, "Licensed under CC BY-NC 4.0."), (5, "license mit public general"), (None, "…")]
    rows += [(6, "word " * 4000 + "mit license"), (7, "Permission is hereby granted, free of charge, to any person obtaining a copy of this software")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("score", F.lit("clash"))
    got = {(r.doc_id, r.n_words): r for r in scan_licenses(docs).collect()}
    base = [t for t in TEMPLATES if t.base]
    for doc, text in rows:
        w = words(text)
        at = sorted(s for t in base for s in range(len(w)) if w[s : s + len(t.words)] == t.words)
        r = got[doc, len(w)]
        assert (r.n_base, r.first_word, r.last_word) == (len(at), at[0] if at else None, at[-1] if at else None)
        assert r.base_labels == ",".join(sorted({t.label for t in base if any(w[s : s + len(t.words)] == t.words for s in range(len(w)))}))
        assert 0 <= r.score <= 1
    assert got[4, 7].labels == "cc-by-nc" and got[7, 16].labels == "mit" and got[7, 16].base_labels == ""
    assert scan_licenses(docs.limit(0)).count() == 0
