"""Benchmark decontamination by winnowing (DataFrame functions only).

Both sides keep the smallest hash of every ``WINDOW`` consecutive ``GRAM``-word hashes; any span of
``GRAM + WINDOW - 1`` shared words therefore shares a kept hash. Kept hashes of documents are joined
with those of the benchmark and each match is extended: the spans around it are compared word
for word with the benchmark's spans, so hash collisions never count. Benchmark items with fewer words
than a span are found through their first word and compared whole.

The benchmark side is broadcast while it has at most ``BROADCAST_ROWS`` spans (13 words each: about a
hundred MB); then document words are read once, and only matches and one marker a document move. Beyond that
kept grams move with their place alone, what they match is gathered for each document (never more than its own
length), and the words around come from one join with the texts.

Defined cases: null and empty texts have no words and no hits; word-free benchmark items and an
empty benchmark hit nothing; an empty document table gives no rows; documents with equal doc_id and
text each keep their row; rows that share a doc_id but not a text are told apart; other columns are
ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.lineage import cut
from sparkcurate.llm.native import words

SPAN = 13
GRAM = 7
WINDOW = SPAN - GRAM + 1
BROADCAST_ROWS = 200_000
# a kept value has a gram's hash above and the low bits of its position below
POSITION_BITS = 20
POSITION_MASK = (1 << POSITION_BITS) - 1


def _valued(words_col: str) -> Column:
    """For each gram: its hash with the low bits replaced by the gram's position."""
    w = F.col(words_col)
    last = F.size(w) - GRAM
    grams = F.transform(F.sequence(F.lit(0), last), lambda i: F.shiftleft(F.shiftright(F.xxhash64(*[F.get(w, i + j) for j in range(GRAM)]), POSITION_BITS), POSITION_BITS).bitwiseOR(i.cast("long").bitwiseAND(F.lit(POSITION_MASK))))
    return F.when(last >= 0, grams).otherwise(F.array().cast("array<bigint>"))


def _kept(values_col: str) -> Column:
    """Positions of the kept grams: the smallest of every full window (of all, if there are fewer)."""
    v = F.col(values_col)
    windows = F.greatest(F.size(v) - WINDOW, F.lit(0))

    def position(j: Column) -> Column:
        low = F.array_min(F.slice(v, j + 1, WINDOW)).bitwiseAND(F.lit(POSITION_MASK))
        return j + (low - j.cast("long")).bitwiseAND(F.lit(POSITION_MASK)).cast("int")

    return F.when(F.size(v) > 0, F.array_distinct(F.transform(F.sequence(F.lit(0), windows), position))).otherwise(F.array().cast("array<int>"))


def kept_grams(rows: DataFrame, words_col: str) -> DataFrame:
    """Adds ``__v`` (gram values) and ``__p`` (positions of kept grams)."""
    return rows.withColumn("__v", _valued(words_col)).withColumn("__p", _kept("__v"))


def _gram_hash(at: Column) -> Column:
    return F.shiftright(F.get(F.col("__v"), at), POSITION_BITS)


def _spans(benchmark: DataFrame) -> DataFrame:
    """Distinct spans of the benchmark with the items that hold them."""
    base = benchmark.select(F.col("item_id").cast("string").alias("__item"), words(F.col("text")).alias("__b"))
    size = F.least(F.size("__b"), F.lit(SPAN))
    starts = F.when(F.size("__b") > 0, F.sequence(F.lit(1), F.size("__b") - size + 1)).otherwise(F.array().cast("array<int>"))
    cut = base.select("__item", "__b", size.alias("__size"), F.explode(starts).alias("__start")).select("__item", F.slice("__b", F.col("__start"), F.col("__size")).alias("__span"))
    return cut.groupBy("__span").agg(F.collect_set("__item").alias("__items"))


def _gram_at(at: Column) -> Column:
    return F.when(at >= 0, _gram_hash(at))


def _around(rows: DataFrame) -> DataFrame:
    """The spans of SPAN words that hold the gram at ``__at``; the whole row for a marker (-1)."""
    first = F.greatest(F.col("__at") - (SPAN - GRAM), F.lit(0))
    near = rows.select("doc_id", "__text", "__n", F.when(F.col("__at") >= 0, first).alias("__first"), F.when(F.col("__at") >= 0, F.slice("__w", first + 1, 2 * SPAN - GRAM)).alias("__around"), "__at")
    shifts = F.when(F.col("__at") >= 0, F.filter(F.sequence(F.lit(0), F.lit(SPAN - GRAM)), lambda d: d + SPAN <= F.size("__around"))).otherwise(F.array(F.lit(-1)))
    spread = near.withColumn("__shift", F.explode(shifts)).withColumn("__span", F.when(F.col("__shift") >= 0, F.slice("__around", F.col("__shift") + 1, SPAN)))
    return spread.select("doc_id", "__text", "__n", (F.col("__first") + F.col("__shift")).alias("__from"), "__span")


def _few(keyed: DataFrame, prints: DataFrame, spans: DataFrame) -> DataFrame:
    """Matches and markers with the benchmark broadcast: no row of a document moves."""
    probes = keyed.select("doc_id", "__text", "__n", "__w", "__v", F.explode(F.concat(F.array(F.lit(-1)), F.col("__p"))).alias("__at")).withColumn("__gram", _gram_at(F.col("__at")))
    marked = probes.join(F.broadcast(prints.withColumn("__hit", F.lit(True))), "__gram", "left").filter((F.col("__at") < 0) | F.col("__hit"))
    matched = _around(marked).join(F.broadcast(spans), "__span", "left")
    return matched.filter(F.col("__items").isNotNull() | F.col("__from").isNull()).drop("__span")


def _many(keyed: DataFrame, prints: DataFrame, spans: DataFrame) -> DataFrame:
    """The same by shuffles of (gram, document, place); markers never meet a join."""
    # with the marker no list is empty, so no filter on the list's size, which would work it out once for each place, comes before
    probes = keyed.select("doc_id", "__text", "__v", F.explode(F.concat(F.array(F.lit(-1)), F.col("__p"))).alias("__at")).filter(F.col("__at") >= 0).select("doc_id", "__text", "__at", _gram_hash(F.col("__at")).alias("__gram"))
    hits = probes.join(prints, "__gram", "left_semi").groupBy("doc_id", "__text").agg(F.collect_set("__at").alias("__ats"))
    named = hits.select(F.col("doc_id").alias("__id"), F.col("__text").alias("__own"), "__ats")
    found = keyed.join(named, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__text") == F.col("__own"))).withColumn("__at", F.explode("__ats"))
    matched = _around(found.select("doc_id", "__text", "__n", "__w", "__at")).join(spans, "__span").drop("__span")
    markers = keyed.select("doc_id", "__text", "__n", F.lit(None).cast("int").alias("__from"), F.lit(None).cast("array<string>").alias("__items"))
    return matched.select("doc_id", "__text", "__n", "__from", "__items").unionByName(markers)


def find_spans(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row a document and match (plus one without a match a document).

    Columns: doc_id, __text (hash that tells texts of one doc_id apart), __n (words), __from and __to
    (matched words, to exclusive; null in the row without a match), __items.
    """
    spans = cut(_spans(benchmark))
    count, short = spans.select(F.count(F.lit(1)), F.max((F.size("__span") < SPAN).cast("int"))).first()
    rows = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text")).select("doc_id", F.xxhash64("text").alias("__text"), words(F.col("text")).alias("__w"))
    keyed = kept_grams(rows, "__w").withColumn("__n", F.size("__w"))
    long_spans = spans.filter(F.size("__span") == SPAN)
    prints = kept_grams(long_spans, "__span").select(F.explode("__p").alias("__at"), "__v").select(_gram_hash(F.col("__at")).alias("__gram")).distinct()
    out = (_few if count <= BROADCAST_ROWS else _many)(keyed, prints, long_spans).withColumn("__to", F.col("__from") + SPAN)
    if short:
        brief = spans.filter(F.size("__span") < SPAN).withColumn("__head", F.get("__span", F.lit(0)))
        brief = F.broadcast(brief) if count <= BROADCAST_ROWS else brief
        each = rows.select("doc_id", "__text", "__w", F.posexplode("__w").alias("__from", "__head"))
        same = F.slice(F.col("__w"), F.col("__from") + 1, F.size("__span")) == F.col("__span")
        if count > BROADCAST_ROWS:
            # the longest brief span is a word shorter than SPAN, so a word moves with those behind it and not with its text
            each = rows.select("doc_id", "__text", F.posexplode(F.transform("__w", lambda w, i: F.slice("__w", i + 1, SPAN - 1))).alias("__from", "__w")).withColumn("__head", F.get("__w", F.lit(0)))
            same = F.slice(F.col("__w"), F.lit(1), F.size("__span")) == F.col("__span")
        hits = each.join(brief, "__head").filter(same)
        out = out.unionByName(hits.select("doc_id", "__text", F.lit(None).cast("int").alias("__n"), "__from", (F.col("__from") + F.size("__span")).alias("__to"), "__items"))
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Hit words and items of every document; ``contaminated`` if at least a twentieth of its words is hit."""
    spans = find_spans(docs, benchmark)
    per = spans.groupBy("doc_id", "__text").agg(
        F.max("__n").alias("__n"), F.sum(F.when(F.col("__from").isNull(), 1).otherwise(0)).alias("__copies"),
        F.collect_set(F.when(F.col("__from").isNotNull(), F.struct(F.col("__from").alias("f"), F.col("__to").alias("t")))).alias("__places"),
        F.array_distinct(F.flatten(F.collect_set("__items"))).alias("__items"),
    )
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
    covered = F.aggregate(F.array_sort("__places"), start, lambda acc, p: F.struct((acc["n"] + F.greatest(p["t"] - F.greatest(p["f"], acc["end"]), F.lit(0))).alias("n"), F.greatest(acc["end"], p["t"]).alias("end")))["n"].cast("long")
    told = per.select(
        "doc_id", "__text", "__copies", F.col("__n").cast("long").alias("n_words"), covered.alias("n_hit"), F.size("__items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.array_sort("__items")), 256).alias("items_sha256"),
    ).withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))
    return told.withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__copies")))).drop("__copies", "__copy")
