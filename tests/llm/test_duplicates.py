import collections
import hashlib
import random

import pytest
from pyspark.sql import functions as F

from sparkcurate.llm.jaccard_join import forest_depth, keep_one_of_each, similar_documents
from sparkcurate.llm.parsing_dedup import SMALLEST, remove_repeats
from sparkcurate.llm.spotsigs import ANCHORS, fingerprint_neighbours, fingerprints, similar_pairs
from tests.llm.test_native import words


def brute_join(rows):
    sets = []
    for _, text in rows:
        w = words(text)
        sets.append(frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else []))
    holders = collections.defaultdict(set)
    for i, s in enumerate(sets):
        for g in s:
            holders[g].add(i)
    top, links = list(range(len(rows))), [0] * len(rows)

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    for i, s in enumerate(sets):
        met = collections.Counter(j for g in s for j in holders[g]) if s else {j: 0 for j, t in enumerate(sets) if not t}
        for j, both in met.items():
            if j != i and (s == sets[j] or 5 * both >= 4 * (len(s) + len(sets[j]) - both)):
                links[i] += 1
                a, b = find(i), find(j)
                top[max(a, b)] = min(a, b)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(least.get(find(i), d), d)
    return sorted(((d, least.get(find(i)), links[i]) for i, (d, _) in enumerate(rows)), key=str)


@pytest.mark.parametrize("block", [2048, 2])
def test_join_equals_brute_force(spark, sf, block):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    got = sorted((tuple(r)[:3] for r in similar_documents(docs, block=block).collect()), key=str)
    assert got == brute_join([tuple(r) for r in docs.collect()])


def test_join_cases(spark):
    rows = [(1, "a b c d e f g h"), (1, "a b c d e f g h"), (2, None), (3, ""), (4, "zz foo"), (None, "foo bar"), (5, "zz FOO"), (None, "zz foo")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("node", F.lit(1))
    assert sorted((tuple(r)[:3] for r in similar_documents(docs).collect()), key=str) == brute_join(rows)
    assert similar_documents(docs.limit(0)).count() == 0
    assert sorted(str(r.doc_id) for r in keep_one_of_each(docs).collect()) == ["1", "2", "4", "None"]
    assert 1 - (1 - 0.8 ** forest_depth(0.8)) ** 32 >= 0.9999


@pytest.mark.parametrize("n", range(8))
def test_join_of_one_short_text(spark, n):
    docs = spark.createDataFrame([(1, " ".join("abcdefgh"[:n]))], "doc_id long, text string").coalesce(1)
    assert [tuple(r) for r in similar_documents(docs).collect()] == [(1, 1, 0, 1)]


def test_one_kept_of_every_class(spark):
    rows = [(1, "a b c d e f g h"), (1, "a b c d e f g h"), (4, "zz foo"), (None, "foo bar"), (None, "zz foo"), (None, "bar bar"), (None, "Foo BAR"), (7, "one two"), (7, "three four"), (8, "THREE four"), (9, None), (None, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = collections.Counter((r.doc_id, (r.text or "").lower()) for r in keep_one_of_each(docs).collect())
    assert got == collections.Counter([(1, "a b c d e f g h"), (4, "zz foo"), (None, "foo bar"), (None, "bar bar"), (7, "one two"), (7, "three four"), (9, "")])


def brute_repeats(rows, span=50):
    first, texts = {}, [((SMALLEST if d is None else d), (t or "").encode()) for d, t in rows]
    for d, t in texts:
        for s in range(len(t) - span + 1):
            first[t[s : s + span]] = min(first.get(t[s : s + span], d), d)
    out = []
    for (doc, _), (d, t) in zip(rows, texts, strict=True):
        gone = bytearray(len(t))
        for s in range(len(t) - span + 1):
            if first[t[s : s + span]] < d:
                gone[s : s + span] = b"\1" * span
        runs = sum(1 for i in range(len(t)) if gone[i] and (i == 0 or not gone[i - 1]))
        out.append((doc, len(t), sum(gone), runs, hashlib.sha256(bytes(c for c, g in zip(t, gone, strict=True) if not g)).hexdigest()))
    return sorted(out, key=str)


def repeats(docs, **options):
    found = remove_repeats(docs, **options).select("doc_id", "n_bytes", "n_removed", F.size("spans"), F.sha2("kept", 256))
    return sorted((tuple(r) for r in found.collect()), key=str)


def test_repeats_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang")
    assert repeats(docs) == brute_repeats([tuple(r)[:2] for r in docs.collect()])


@pytest.mark.parametrize("hot", [1000, 5, 0])
def test_repeats_cases(spark, hot):
    rng = random.Random(3)
    rows = [(i, "".join(rng.choice("ab") for _ in range(rng.choice([0, 40, 120, 300])))) for i in range(30)]
    rows += [(50, "a" * 400), (51, "x" + "a" * 120), (7, "b" * 90), (7, "b" * 60), (52, None), (53, ""), (None, "a" * 70), (None, "qq" + "a" * 70)] + [(60 + i, "é" * i) for i in range(20, 40)]
    long = "".join(rng.choice("ab cd") for _ in range(2000))
    rows += [(100, long), (101, long[500:900] + "zz" + long[100:160]), (101, long[500:900] + "zz" + long[100:160]), (102, long[:49]), (103, "t" + long[3:53] + "u")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert repeats(docs, hot=hot) == brute_repeats(rows)
    assert repeats(docs.limit(0)) == []


def test_spotsigs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r.doc_id: r for r in fingerprint_neighbours(docs).collect()}
    order = sorted(docs.select("doc_id", "text").collect(), key=lambda r: -r.doc_id)
    by_text = {}
    for i, r in enumerate(order):
        following, n = order[(i + 1) % len(order)].text, len(r.text)
        edited = r.text[: n - n // 3] + following[: n // 3]
        assert rows[r.doc_id].n_chars == n and rows[r.doc_id].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert by_text.setdefault(r.text, rows[r.doc_id].fingerprint) == rows[r.doc_id].fingerprint
    assert sum(r.near_edited for r in rows.values()) / len(rows) > 0.4 > 0.1 > sum(r.near_next for r in rows.values()) / len(rows)
    pairs, members = similar_pairs(docs)
    spots = {r.doc_id: set(r.spots) for r in fingerprints(docs).collect()}
    heads = sorted({r.member for r in members.collect()})
    expected = {(a, b) for i, a in enumerate(heads) for b in heads[i + 1 :] if spots[a] and spots[b] and len(spots[a] & spots[b]) >= 0.8 * len(spots[a] | spots[b]) - 1e-12}
    assert {tuple(sorted((r.a, r.b))) for r in pairs.collect()} == expected


def brute_spots(text):
    anchors, w, found = set(ANCHORS), words(text), set()
    for i, word in enumerate(w):
        if word in anchors:
            chain = [x for x in w[i + 1 :] if x not in anchors][:2]
            if len(chain) == 2:
                found.add((word, *chain))
    return found or ({("all words", *w)} if w else set())


def test_spotsigs_equal_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + [(None, "the cat sat on the mat"), (None, "the dog ran"), (None, None), (-7, "one two"), (-7, "one two"), (-7, "der Hund bellt laut")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    # falling doc_id, null last; texts of one id by the falling hash of the text
    order = [tuple(r) for r in docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).orderBy(F.desc_nulls_last("doc_id"), F.desc(F.xxhash64("text"))).collect()]
    like = lambda a, b: 1.0 if not a and not b else len(a & b) / len(a | b)
    expected = []
    for i, (doc, text) in enumerate(order):
        after, n = order[(i + 1) % len(order)][1], len(text)
        edited = text[: n - n // 3] + after[: n // 3]
        own = brute_spots(text)
        expected.append((doc, n, len(own), len(brute_spots(edited)), round(like(own, brute_spots(edited)), 9), round(like(own, brute_spots(after)), 9)))
    for chunk_rows in (3, 40, 10_000):
        got = [(r.doc_id, r.n_chars, len(r.fingerprint) // 8, len(r.edited_fingerprint) // 8, round(r.near_edited, 9), round(r.near_next, 9)) for r in fingerprint_neighbours(docs, chunk_rows=chunk_rows).collect()]
        assert sorted(got, key=str) == sorted(expected, key=str)


def test_spotsigs_of_one_hot_id(spark):
    docs = spark.range(4000).select(F.when(F.col("id") % 4 == 0, F.col("id")).alias("doc_id"), F.concat(F.lit("the cat "), F.col("id").cast("string")).alias("text"))
    assert fingerprint_neighbours(docs, chunk_rows=100).select(F.count(F.lit(1)), F.count("doc_id"), F.countDistinct("fingerprint")).first() == (4000, 1000, 4000)


def test_spotsigs_cases(spark):
    rows = [(1, "the a cat sat on"), (1, "the cat"), (2, None), (None, ""), (3, "123 !!"), (None, "日本"), (3, "123 !!")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("chunk", F.lit(1))
    for chunk_rows in (2, 500):
        assert fingerprint_neighbours(docs, chunk_rows=chunk_rows).count() == len(rows)
    assert fingerprint_neighbours(docs.limit(0)).count() == 0
    assert fingerprint_neighbours(docs.filter("doc_id = 2")).first().near_next == 1.0
