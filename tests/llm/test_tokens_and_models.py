import base64
import random
import zlib

import numpy as np
import public_tokenizers as P
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from sparkcurate.functions.arrow import map_arrow
from sparkcurate.llm import language_id as li
from sparkcurate.llm import toxicity as tx
from sparkcurate.llm.packing import WordEncoder, pack, pack_documents, partition
from sparkcurate.llm.token_counts import RankEncoder, attribute, section_tokens

PATH = P.path("word_bpe_49k.json")


def check_pieces(rows, docs):
    tokenizer = Tokenizer.from_file(PATH)
    by = dict(list(rows.groupby("doc_id")))
    for doc, text in docs:
        ids, at = tokenizer.encode(text or "", add_special_tokens=False).ids + [2], 0
        for r in by[doc].sort_values("start").itertuples():
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    for _, s in rows.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert (s.offset == s.length.cumsum() - s.length).all() and s.length.sum() <= 4096


def test_packing(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = pack_documents(docs, PATH).toPandas()
    check_pieces(rows, docs.select("doc_id", "text").collect())
    assert rows.length.sum() / (4096 * rows.sequence_id.nunique()) > 0.95


def test_packing_cases(spark):
    odd = [(1, "It's A.B. don’t İstanbul ǆ 12,5 ... été. x\x1cy <|endoftext|> 日本。"), (2, None), (3, ""), (4, "x " * 9000), (5, "Été, ÉTÉ; naïve: «quoted». a1. ½. a!! b?! É!")]
    docs = spark.createDataFrame(odd, "doc_id long, text string").withColumn("pack", F.lit("clash"))
    check_pieces(pack_documents(docs, PATH).toPandas(), odd)
    again = spark.createDataFrame([(1, "a b")] * 3 + [(None, "c")], "doc_id long, text string")
    assert pack_documents(again, PATH).count() == 4
    assert pack_documents(docs.limit(0), PATH).count() == 0


def test_ids_equal_the_tokenizer():
    rng = random.Random(11)
    letters = ["a", "b", "E", "İ", "ı", "I", "H", "\u0331", "ß", "ſ", "ñ", "É", "e\u0301", "\u0301", "\u0307", "क", "\u093c", "ड\u093c", "日", "ﬀ", "ǅ", "ŉ", "Ω", "ς", "Σ", "ж", "ª", "½", "1", "٣", "_", "'"]
    others = [".", ",", "!", "?", ";", ":", "'s", "'LL", "’", "…", "。", " ", " ", " ", "\t", "\n", "\u00a0", "\u3000", "\x1c", "\x85", "\u200b", "<|endoftext|>", "<|ENDOFTEXT|>", "<|", "|>", "😀", "\ufeff"]
    texts = ["".join(rng.choice(letters if rng.random() < 0.7 else others) for _ in range(rng.randrange(1, 24))) for _ in range(20_000)] + ["BELEDİYESİ. x", "a<|endoftext|>b. c"]
    tokenizer, encode = Tokenizer.from_file(PATH), WordEncoder(PATH)
    expected = [np.array(e.ids, "<u4").tobytes() for e in tokenizer.encode_batch(texts, add_special_tokens=False)]
    for x in range(0, len(texts), 500):
        assert list(encode([t.encode() for t in texts[x : x + 500]])) == expected[x : x + 500]


def test_packing_of_one_repeated_row(spark):
    docs = spark.createDataFrame([(1, "a b c")], "doc_id long, text string").withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(9000))))
    rows = pack_documents(docs, PATH, group=500).toPandas()
    assert len(rows) == 9000 and rows.groupby("sequence_id").length.sum().max() <= 4096
    assert rows.sequence_id.floordiv(1 << 32).nunique() > 10


def test_differencing():
    sizes = np.array([8, 7, 6, 5, 4])
    assert abs(np.bincount(partition(sizes, 2), weights=sizes) - 15).max() <= 1
    sizes = np.random.default_rng(1).integers(1, 4096, 300)
    sums = np.bincount(pack(sizes, 4096), weights=sizes)
    assert sums.max() <= 4096 and sums.sum() == sizes.sum()
    assert list(pack(np.array([4000, 4000]), 4096)) in ([0, 1], [1, 0])


def test_section_tokens(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60)
    rows = section_tokens(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).toPandas()
    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as file:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}
    encoding = tiktoken.Encoding("test", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    sums = rows.groupby("doc_id")[["tokens_start", "tokens_majority", "tokens_share"]].sum()
    for doc, text in docs.select("doc_id", "text").collect():
        n = len(encoding.encode_ordinary(text))
        assert sums.loc[doc].tokens_start == n == sums.loc[doc].tokens_majority and abs(sums.loc[doc].tokens_share - n) < 1e-3
    odd = spark.createDataFrame([(1, None), (2, ""), (None, "a\n\nb"), (2, "")], "doc_id long, text string")
    assert section_tokens(odd, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == 6
    assert section_tokens(odd.limit(0), P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == 0


def byte_encoding():
    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as file:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}
    return tiktoken.Encoding("test", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_sections_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").filter("length(text) < 6000").limit(40).select("doc_id", "text")
    encoding, expected = byte_encoding(), {}
    for doc, text in docs.collect():
        tokens, at = [], 0
        for t in encoding.encode_ordinary(text):
            size = len(encoding.decode_single_token_bytes(t))
            tokens.append((at, at + size))
            at += size
        lines = text.split("\n")
        sections = [line + "\n" for line in lines[:-1]] + ([lines[-1]] if lines[-1] or len(lines) == 1 else [])
        begin = chars = 0
        for n, section in enumerate(sections):
            end = begin + len(section.encode())
            held = [(min(b, end) - max(a, begin), a, b) for a, b in tokens if min(b, end) > max(a, begin)]
            majority = 0
            for own, a, b in held:
                spread, place = [], 0
                for other in sections:
                    stop = place + len(other.encode())
                    spread.append(max(0, min(b, stop) - max(a, place)))
                    place = stop
                majority += spread.index(max(spread)) == n
            expected[doc, n] = (
                chars, chars + len(section), sum(begin <= a < end for _, a, b in held), majority,
                round(sum(own / (b - a) for own, a, b in held), 6), sum(own < b - a for own, a, b in held),
            )
            begin, chars = end, chars + len(section)
    got = {(r[0], r[1]): tuple(r)[2:] for r in section_tokens(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).collect()}
    assert got.keys() == expected.keys()
    for k, (a, b, start, majority, share, crossing) in expected.items():
        assert got[k][:4] == (a, b, start, majority) and abs(got[k][4] - share) < 1e-5 and got[k][5] == crossing


def test_sections_of_long_white_space(spark):
    encoder, encoding = RankEncoder(P.path("byte_bpe_50k.tiktoken"), P.PATTERN), byte_encoding()
    rng = random.Random(4)
    for _ in range(60):
        text = "".join(rng.choice([" ", "\n", "\u3000", "\t", "a", "it's", "1", ".", "é"]) * rng.choice([1, 1, 2, 999, 1000, 1001, 3000]) for _ in range(6))
        assert encoder.ranks(text) == encoding.encode_ordinary(text)
    docs = spark.createDataFrame([(1, "a" + " " * 2_000_000 + "b"), (2, "\n" * 1500)], "doc_id long, text string")
    rows = section_tokens(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).groupBy("doc_id").agg(F.sum("tokens_start"), F.count(F.lit(1))).orderBy("doc_id").collect()
    assert rows[0][1] == 2_000_001 and rows[1][2] == 1500


def test_boundary_rules():
    # tokens [0, 3) [3, 8) [8, 10); sections [0, 4) [4, 10)
    found = attribute(np.array([3, 8, 10]), np.array([0, 4, 10]))
    assert list(found["start"]) == [2, 1] and list(found["majority"]) == [1, 2] and list(found["crossing"]) == [1, 1]
    assert np.allclose(found["share"], [1.2, 1.8])


def test_language(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = li.identify_languages(docs).join(docs.select("doc_id", "lang"), "doc_id").filter("held_out")
    assert rows.filter("lang = lang_pred").count() >= 0.97 * rows.count()
    odd = spark.createDataFrame([(1, "a b the of", "en"), (2, None, "fr"), (None, "", None), (3, "123 !!", None), (None, "日本", "ja")], "doc_id long, text string, lang string")
    got = sorted((str(r.doc_id), r.lang_pred) for r in li.identify_languages(odd).collect())
    assert got == [("1", "en"), ("2", "und"), ("3", "und"), ("None", "ja"), ("None", "und")]
    assert li.identify_languages(odd.limit(0)).count() == 0
    assert li.keep_identified(odd).columns == odd.columns


def test_languages_of_large_alphabets(spark):
    rng = random.Random(5)
    spans = {"ja": (0x3041, 0x3090), "zh": (0x4E00, 0x4E00 + 2500), "ko": (0xAC00, 0xAC00 + 2000), "am": (0x1200, 0x1240), "el": (0x3B1, 0x3C9)}
    words = {lang: ["".join(chr(rng.randrange(*span)) for _ in range(3)) for _ in range(300)] for lang, span in spans.items()}
    rows = [(i, " ".join(rng.choice(words[lang]) for _ in range(60)), lang) for i, lang in enumerate(sorted(spans) * 40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    told = {r.doc_id: r.lang_pred for r in li.identify_languages(docs).filter("held_out").collect()}
    assert len(told) > 20 and all(told[i] == lang for i, _, lang in rows if i in told)


def test_sparse_automaton_equals_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    samples, texts = li.learn_samples(docs.limit(40)), [r.text for r in docs.limit(20).collect()]
    assert li.CrossParser(samples, dense_cells=0).predict(texts) == li.CrossParser(samples).predict(texts)
    assert li.letters("Ａｂ　日").tolist() == [ord("ａ"), ord("ｂ"), 32, ord("日")]


def test_cross_parse_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    samples = li.learn_samples(docs.limit(40))
    parser = li.CrossParser(samples)
    coded = [parser.encode(li.letters(row.text))[:1500] for row in docs.limit(8).collect()]
    coded.append(np.full(300, 2, parser.kind))
    expected = []
    for text in map(bytes, coded):
        own = []
        for _, sample in samples:
            known, phrases, i = bytes(parser.encode(li.letters(sample)[: li.SAMPLE_LETTERS])), 0, 0
            while i < len(text):
                j = i + 1
                while j <= len(text) and text[i:j] in known:
                    j += 1
                phrases, i = phrases + 1, max(j - 1, i + 1)
            own.append(phrases)
        expected.append(own)
    for lanes in (1, 3, 100):
        assert parser.phrases(coded, lanes).tolist() == expected


def test_letters_of_long_texts(monkeypatch):
    text = "  Ab,c  " * 7 + " É日 1x "
    whole = li.letters(text).tolist()
    for size in (1, 2, 3, 5):
        monkeypatch.setattr(li, "_CHARACTERS", size)
        assert li.letters(text).tolist() == whole
    assert "".join(map(chr, whole)).endswith("ab c é日 x")


def test_columns_of_any_name_stay(spark):
    rows = [(1, "the of and it", "en", 1, "x", 2, "r"), (None, "le la les et", "fr", 2, "y", 3, "s"), (2, "..", "en", 3, "z", 4, "t"), (3, "le des une", "fr", 4, "w", 5, None)]
    docs = spark.createDataFrame(rows, ["doc_id", "text", "lang", "a.b", "my col", "n_bytes", "rest"])
    kept = li.keep_identified(docs)
    assert kept.columns == docs.columns and kept.schema["my col"].dataType == docs.schema["my col"].dataType
    assert sorted((str(r[0]), r[1], r[3], r[4], r[5], r[6]) for r in kept.collect()) == sorted((str(r[0]), r[1], *r[3:]) for r in rows if r[1] != "..")


def test_toxicity(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    rows = tx.score_toxicity(docs, labels).join(labels, "doc_id").join(docs.select("doc_id", "text"), "doc_id").filter("held_out").toPandas()
    plain = rows.text.str.lower().str.contains(r"\b(?:idiot|moron|stupid|loser|pathetic|trash|scum|worthless|disgusting|clown)\b")
    assert (rows.predicted[plain] == 1).all() and rows.predicted[(rows.toxic == 0)].mean() < 0.03
    odd = spark.createDataFrame([(1, "you idiot", 1), (1, "a b", 0), (2, None, 0), (None, "", 0)], "doc_id long, text string, toxic int")
    assert tx.score_toxicity(odd, odd).filter("score between 0 and 1").count() == 4
    assert tx.score_toxicity(odd.limit(0), odd).count() == 0
    assert tx.score_toxicity(odd, odd.limit(0)).count() == 4


def test_isotonic_is_monotone():
    x, y = tx.isotonic(np.array([1.0, 2, 3, 4, 4, 5]), np.array([0.0, 1, 0, 0, 1, 1]))
    assert (np.diff(y) >= 0).all() and np.isclose(np.interp(2.0, x, y), 0.5)
    assert np.isclose(y[-1], 1.0)


def test_workers_drop_the_models_of_other_operators(spark, sf):
    def held(batches):
        import gc

        import pyarrow as pa

        for _ in batches:
            pass
        yield pa.RecordBatch.from_arrays([pa.array([sum(type(x).__name__ in ("CrossParser", "WordEncoder") for x in gc.get_objects())])], ["n"])

    docs = spark.read.parquet(f"{sf}/documents.parquet").repartition(8)
    ids = spark.range(8).repartition(8)
    li.identify_languages(docs).write.format("noop").mode("overwrite").save()
    assert {r.n for r in map_arrow(ids, held, "n long").collect()} == {0}
    pack_documents(docs, PATH).write.format("noop").mode("overwrite").save()
    assert {r.n for r in map_arrow(ids, held, "n long").collect()} == {0}


def test_pipeline(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    now, sizes = docs, [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        now = spark.createDataFrame(stage(spark, now, sf).toPandas(), docs.schema)
        assert now.columns == docs.columns
        sizes.append(now.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0.8 * sizes[0]
    by_hand = corpus_pipeline.STAGES[-1][1](spark, now, sf).agg(F.sum("length")).first()[0]
    assert corpus_pipeline.run(spark, sf).agg(F.sum("length")).first()[0] == by_hand


def test_split_choice_equals_brute_force(monkeypatch):
    rng = np.random.default_rng(3)
    x = rng.integers(0, 6, (80, 3)).astype(float)
    y = ((x[:, 1] > 2) ^ (rng.random(80) < 0.1)).astype(float)
    monkeypatch.setattr(tx, "TREES", 1)
    trees = tx.BoostedTrees().fit(x, y)
    chance = y.mean()
    slope, weight = y - chance, np.full(80, chance * (1 - chance))
    binned, best = trees.bins(x), (0.0, None)
    for j in range(3):
        for cut in range(6):
            left = binned[:, j] <= cut
            parts = [(slope[m].sum(), weight[m].sum()) for m in (left, ~left)]
            if min(h for _, h in parts) >= tx.LEAST_WEIGHT:
                gain = sum(g * g / (h + tx.SHRINK) for g, h in parts) - slope.sum() ** 2 / (weight.sum() + tx.SHRINK)
                if gain > best[0] + 1e-12:
                    best = (gain, (j, cut))
    j, cut = best[1]
    assert trees.column[0][0] == j == 1
    assert ((binned[:, j] <= cut) == (binned[:, j] <= trees.split[0][0])).all()
    # the leaf of each row is the regularised mean slope of its rows
    margin = trees.margin(x)
    for value in np.unique(margin):
        rows = margin == value
        leaf = tx.RATE * slope[rows].sum() / (weight[rows].sum() + tx.SHRINK)
        assert np.isclose(value - trees.base, leaf) or len(np.unique(margin)) < 8


def test_learned_words_are_found(spark):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    rows = [(i, " ".join([word() for _ in range(30)] + ([f"zorq{word()}"] if i % 5 == 0 else [])), int(i % 5 == 0)) for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    told = tx.score_toxicity(docs.drop("toxic"), docs.select("doc_id", "toxic")).join(docs, "doc_id").filter("held_out").toPandas()
    assert (told.predicted[told.toxic == 1] == 1).mean() > 0.95 and (told.predicted[told.toxic == 0] == 0).mean() > 0.95


def test_pipeline_equals_brute_force(spark, tmp_path):
    from tests.llm.test_duplicates import brute_join, brute_repeats
    from tests.llm.test_native import brute_windows

    sf = "/root/testdata/sf0.001"
    some = spark.read.parquet(f"{sf}/documents.parquet").limit(90)
    shared = " ".join(f"passage{i}" for i in range(20))
    extra = [(9001, "the of and it is", "en", "x", 1), (9002, "the of and it is", "en", "x", 1), (9003, " ...", "en", "x", 1), (None, f"one {shared} two", "en", "x", 1), (9004, f"three {shared} four and five", "en", "x", 1), (9004, "the same id but another text", "en", "x", 1)]
    docs = some.unionByName(spark.createDataFrame(extra, some.schema))
    renamed = docs.withColumnsRenamed({"source": "my col"}).withColumn("a.b", F.lit(1)).withColumn("n_bytes", F.lit("own")).withColumn("rest", F.lit(2)).withColumn("spans", F.lit(3)).withColumn("lang_pred", F.lit("p"))
    stages = [s for _, s in corpus_pipeline.STAGES]
    now, names = renamed, renamed.columns
    key = lambda r: (str(r["doc_id"]), r["text"])
    for k, stage in enumerate(stages[:-1]):
        before = [(r["doc_id"], r["text"]) for r in now.select("doc_id", "text").collect()]
        now = spark.createDataFrame(stage(spark, now, sf).collect(), now.schema)
        after = sorted(key(r) for r in now.select("doc_id", "text").collect())
        assert now.columns == names
        if k == 0:
            expected = [(d, t) for d, t in before if t and any(c.isalpha() for c in t)]
        elif k == 1:
            assert len(after) == len({r[1] if r[1] is not None else r for r in brute_join([(i, t) for i, (_, t) in enumerate(before)])})
            expected = None
        elif k == 2:
            gone = {(str(d), n) for d, n, removed, *_ in brute_repeats(before) if not removed}
            assert len(after) == len(before) and all((str(d), t) in after for d, t in before if (str(d), len(t.encode())) in gone)
            assert sum(len(t.encode()) for _, t in after) <= sum(n - removed for _, n, removed, *_ in brute_repeats(before))
            expected = None
        else:
            items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
            bad = {i for i, *_, contaminated in brute_windows([(i, t) for i, (_, t) in enumerate(before)], items) if contaminated}
            expected = [p for i, p in enumerate(before) if i not in bad]
        if expected is not None:
            assert after == sorted((str(d), t) for d, t in expected)
    rows = stages[-1](spark, now, sf).toPandas()
    tokenizer = Tokenizer.from_file(PATH)
    total = sum(len(tokenizer.encode(r["text"], add_special_tokens=False).ids) + 1 for r in now.select("text").collect())
    assert rows.length.sum() == total and rows.groupby("sequence_id").length.sum().max() <= 4096
