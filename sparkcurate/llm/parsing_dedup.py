"""Removal of repeated byte strings by prefix-free parsing: dictionary, parse, and their suffix orders.

A rolling hash over ``GRAM`` bytes sets triggers: the least hash among the grams of a ``SPAN``-byte string
(leftmost, if it recurs) is its trigger, so every such string has one; a fixed remainder would leave strings without.
A text's phrases run from one trigger's strings to the next one's: a phrase holds all strings with one trigger place,
with the ``SPAN - 1`` bytes that follow its last start, so no phrase ends inside a string that begins in it and
what comes after a phrase never decides the order of its suffixes to that depth. Steps:

1. triggers: (trigger hash, document) of the smallest document of each distinct text; only triggers that two
   texts share go on;
2. parse: the phrases of those triggers with their places; the dictionary has each distinct phrase once. The phrases
   of a trigger of more than ``HOT`` documents are combined before they move, and its places, which no task then
   needs together, are joined to the result;
3. suffix array of the dictionary: all suffixes of ``SPAN`` bytes or more of a trigger's phrases, in the order of their
   bytes (the trigger's own gram, equal in all, is left out); a run of suffixes equal in ``SPAN`` bytes is one string;
4. order of the parse: the places of each phrase by document. Both orders together are the corpus order to the
   depth of ``SPAN``: a run's places are those of its phrases, and its smallest document is their least;
5. a phrase goes whole in all but its smallest document; there only strings go whose run has a smaller
   document. Documents whose whole text is that of a smaller one go whole.

Texts move once, compressed, by doc_id, and serve all steps; besides them trigger rows and the phrases of shared
triggers move. A task of step 3 holds the distinct phrases of one trigger.

Defined cases: null text is empty; a null doc_id counts as smaller than all others; rows of one doc_id
never remove each other's bytes, so repeated rows have the same result; texts below ``SPAN`` bytes stay
whole; an empty table gives no rows; other columns pass through, whatever their names, but in ``remove_repeats``
its own columns take the place of those with the same names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, LongType, StructField, StructType

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.llm.native import quoted
from sparkcurate.llm.textscan import _INVERSE, SLICE_BYTES, distinct_by_row, mix, powers, prefix_hash, slices, span_hash

SPAN = 50
GRAM = 20
SMALLEST = -(1 << 63)
# documents of a trigger from which its phrases are combined before they meet
HOT = 8192
# phrases that are sent, and phrases that are ordered, at once
_ROWS = 20_000


def _window_minima(data: np.ndarray, offsets: np.ndarray, span: int, gram: int):
    """Gram hashes, the start of every whole span inside a text, its row, and its smallest gram hash."""
    n = len(data)
    if n < span:
        nothing = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), nothing, nothing, np.zeros(0, np.uint64)
    prefix = prefix_hash(data)
    hashes = mix((prefix[gram:] - prefix[:-gram]) * powers(_INVERSE, n + 1)[: n - gram + 1])
    del prefix
    low, have, need = hashes, 1, span - gram + 1
    while have < need:
        step = min(have, need - have)
        low = np.minimum(low[: len(low) - step], low[step:])
        have += step
    # low[s] is valid for the starts of spans that do not leave their text
    usable = np.ones(n - span + 1, bool)
    for end in offsets[1:-1].tolist():
        usable[max(0, end - span + 1) : end] = False
    starts = np.flatnonzero(usable)
    rows = np.searchsorted(offsets, starts, "right") - 1
    return hashes, starts, rows, low[starts]


def _zip(columns: list[str]):
    """Texts compressed one by one for the way to their partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = zstandard.ZstdCompressor(level=3)
        for batch in slices(batches):
            texts = batch.column("text").cast(pa.binary()).to_pylist()
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array([packer.compress(t) for t in texts], pa.binary()), pa.array([len(t) for t in texts], pa.int64())], [*columns, "packed", "n_bytes"])

    return run


def _unzipped(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Rows with their texts, some megabytes at a time."""
    opener = zstandard.ZstdDecompressor()
    for batch in batches:
        group = np.cumsum(np.asarray(batch.column("n_bytes"))) // SLICE_BYTES
        cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b > a:
                part = batch.slice(a, b - a)
                yield part, [opener.decompress(t) for t in part.column("packed").to_pylist()]


def _joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])])


def _triggers(span: int, gram: int):
    """(trigger, document), once for each slice of texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in _unzipped(batches):
            _, _, rows, low = _window_minima(*_joined(texts), span, gram)
            change = np.ones(len(low), bool)
            change[1:] = (low[1:] != low[:-1]) | (rows[1:] != rows[:-1])
            low, rows = distinct_by_row(low[change], rows[change])
            yield pa.RecordBatch.from_arrays([pa.array(low.view(np.int64)), batch.column("id").take(pa.array(rows))], ["trigger", "id"])

    return run


def _phrases(span: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in _unzipped(batches):
            data, offsets = _joined(texts)
            hashes, starts, rows, low = _window_minima(data, offsets, span, gram)
            shared = np.unique(np.asarray(batch.column("triggers").flatten())).view(np.uint64)
            shared.sort()
            if not len(shared) or not len(low):
                continue
            change = np.ones(len(low), bool)
            change[1:] = low[1:] != low[:-1]
            firsts = low[change]
            good = (shared[np.minimum(np.searchsorted(shared, firsts), len(shared) - 1)] == firsts)[np.cumsum(change) - 1]
            starts, rows, low = starts[good], rows[good], low[good]
            if not len(starts):
                continue
            place = np.full(len(starts), -1, np.int64)
            for o in range(span - gram, -1, -1):
                same = hashes[starts + o] == low
                place[same] = starts[same] + o
            first = np.ones(len(starts), bool)
            first[1:] = (place[1:] != place[:-1]) | (rows[1:] != rows[:-1]) | (starts[1:] != starts[:-1] + 1)
            begin = np.flatnonzero(first)
            end = np.append(begin[1:], len(starts)) - 1
            a, b, row = starts[begin], starts[end] + span, rows[begin]
            # the trigger's own gram is left out: its hash stands for it, and every span holds it whole
            before = place[begin] - a
            sizes = b - a - gram
            cuts = np.concatenate([[0], np.cumsum(sizes)])
            inside = np.arange(cuts[-1]) - np.repeat(cuts[:-1], sizes)
            content = data[np.repeat(a, sizes) + inside + gram * (inside >= np.repeat(before, sizes))]
            # one row for all places of a phrase in a text: periodic text repeats few phrases very often
            name = span_hash(prefix_hash(content), cuts[:-1], cuts[1:])
            order = np.lexsort((a, before, name, low[begin], row))
            new = np.ones(len(order), bool)
            for v in (before, name, low[begin], row):
                new[1:] &= v[order][1:] == v[order][:-1]
            new[1:] = ~new[1:]
            heads, at = order[new], np.append(np.flatnonzero(new), len(order))
            starts = (a - offsets[row])[order]
            for x in range(0, len(heads), _ROWS):
                y = min(len(heads), x + _ROWS)
                some = heads[x:y]
                size = sizes[some]
                ends = np.concatenate([[0], np.cumsum(size)])
                part = content[np.arange(ends[-1]) + np.repeat(cuts[some] - ends[:-1], size)]
                phrase = pa.Array.from_buffers(pa.binary(), y - x, [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(part.tobytes())])
                places = pa.ListArray.from_arrays(pa.array((at[x : y + 1] - at[x]).astype(np.int32)), pa.array(starts[at[x] : at[y]]))
                r = pa.array(row[some])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(low[begin][some].view(np.int64)), phrase, pa.array(before[some].astype(np.int32)), batch.column("id").take(r), batch.column("twin").take(r), places],
                    ["trigger", "phrase", "before", "id", "twin", "starts"],
                )

    return run


def _dictionary_order(trigger: np.ndarray, before: np.ndarray, data: np.ndarray, cuts: np.ndarray, span: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(phrase, place in it) of every suffix of a span's length or more, the suffix array, and where its runs of equal spans begin."""
    rest = span - gram
    windows = np.diff(cuts) - rest + 1
    owner = np.repeat(np.arange(len(windows)), windows)
    inside = np.arange(len(owner)) - np.repeat(np.cumsum(windows) - windows, windows)
    at = cuts[owner] + inside
    # equal spans have their trigger at the same place
    kind = (np.unique(trigger, return_inverse=True)[1].astype(np.int64)[owner] << 8) + (before[owner] - inside)
    # the bytes without the gram, as big-endian numbers that compare like the bytes
    block = np.zeros((len(owner), -(-rest // 8) * 8), np.uint8)
    for o in range(rest):
        block[:, o] = data[at + o]
    columns = [kind, *block.view(">u8").astype(np.uint64).T]
    order = np.lexsort(columns[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for c in columns:
        c = c[order]
        new[1:] |= c[1:] != c[:-1]
    return owner, inside, order, new


def _order(trigger: np.ndarray, before: np.ndarray, low: np.ndarray, data: np.ndarray, cuts: np.ndarray, span: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(phrase, from, to) of the runs of spans that a smaller document than the phrase's own (low) has."""
    owner, inside, order, new = _dictionary_order(trigger, before, data, cuts, span, gram)
    gone = np.zeros(len(owner), bool)
    if len(order):
        own = low[owner[order]]
        gone[order] = np.minimum.reduceat(own, np.flatnonzero(new))[np.cumsum(new) - 1] < own
    turn, stop = gone.copy(), gone.copy()
    turn[1:] &= ~(gone[:-1] & (owner[1:] == owner[:-1]))
    stop[:-1] &= ~(gone[1:] & (owner[1:] == owner[:-1]))
    a, b = np.flatnonzero(turn), np.flatnonzero(stop)
    return owner[a], inside[a], inside[b] + span


def _ordered(table: pa.Table, span: int, gram: int) -> pa.RecordBatch:
    """For each phrase of a dictionary, the spans (from, to) that a smaller document has."""
    data, cuts = _binary(table.column("phrase"))
    owner, a, b = _order(*(np.asarray(table.column(c)) for c in ("trigger", "before", "low")), data, cuts, span, gram)
    per = np.zeros(table.num_rows + 1, np.int32)
    per[1:] = np.cumsum(np.bincount(owner, minlength=table.num_rows))
    pairs = pa.StructArray.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])
    return pa.RecordBatch.from_arrays([*(table.column(c).combine_chunks() for c in ("trigger", "name", "low")), pa.ListArray.from_arrays(pa.array(per), pairs)], ["trigger", "name", "low", "spans"])


def _resolved(table: pa.Table, span: int, gram: int) -> pa.RecordBatch:
    """For the phrases of whole triggers at their places: the bytes (from, to) that go there."""
    data, cuts = _binary(table.column("phrase"))
    trigger, before, ids, twin = (np.asarray(table.column(c)) for c in ("trigger", "before", "id", "twin"))
    places = table.column("starts").combine_chunks()
    many = np.asarray(places.value_lengths())
    start, at = np.asarray(places.flatten()), np.cumsum(many) - many
    prefix = prefix_hash(data)
    name = span_hash(prefix, cuts[:-1], cuts[1:])
    order = np.lexsort((ids, before, name, trigger))
    new = np.ones(len(order), bool)
    for v in (before, name, trigger):
        new[1:] &= v[order][1:] == v[order][:-1]
    new[1:] = ~new[1:]
    entry = np.empty(len(order), np.int64)
    entry[order] = np.cumsum(new) - 1
    heads = order[new]
    sizes = np.diff(cuts)
    own = np.concatenate([[0], np.cumsum(sizes[heads])])
    content = data[np.arange(own[-1]) + np.repeat(cuts[heads] - own[:-1], sizes[heads])]
    owner, a, b = _order(trigger[heads], before[heads], ids[heads], content, own, span, gram)
    whole = np.flatnonzero(ids > ids[heads][entry])
    # the smallest document's places of a phrase (there may be several) take over its runs
    first = np.flatnonzero(ids == ids[heads][entry])
    first = first[np.argsort(entry[first], kind="stable")]
    lo, hi = np.searchsorted(entry[first], owner), np.searchsorted(entry[first], owner, "right")
    times = hi - lo
    row = first[np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times) + np.repeat(lo, times)]
    row, a, b = np.concatenate([whole, row]), np.concatenate([np.zeros(len(whole), np.int64), np.repeat(a, times)]), np.concatenate([sizes[whole] + gram, np.repeat(b, times)])
    # every run at every place of its phrase, joined where they touch
    times = many[row]
    shift = start[np.repeat(at[row], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)]
    row, a, b = np.repeat(row, times), np.repeat(a, times) + shift, np.repeat(b, times) + shift
    order = np.lexsort((a, twin[row], ids[row]))
    row, a, b = row[order], a[order], b[order]
    if not len(row):
        return pa.RecordBatch.from_arrays([pa.array(v) for v in (ids[row], twin[row], a, b)], ["id", "twin", "a", "b"])
    text = np.ones(len(row), bool)
    text[1:] = (ids[row][1:] != ids[row][:-1]) | (twin[row][1:] != twin[row][:-1])
    # ends so far inside a text: lifted by the text's number, so one running maximum serves all
    lift = (np.cumsum(text) - 1) * (int(b.max()) + 1)
    reach = np.maximum.accumulate(b + lift)
    new = text.copy()
    new[1:] |= a[1:] + lift[1:] > reach[:-1]
    first = np.flatnonzero(new)
    b = (reach - lift)[np.append(first[1:], len(row)) - 1]
    return pa.RecordBatch.from_arrays([pa.array(v) for v in (ids[row[first]], twin[row[first]], a[first], b)], ["id", "twin", "a", "b"])


def _binary(column) -> tuple[np.ndarray, np.ndarray]:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    column = column.cast(pa.large_binary())
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    cuts = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data[cuts[0] : cuts[-1]], cuts - cuts[0]


def _by_trigger(span: int, gram: int, work):
    """Rows arrive sorted by trigger; the rows of whole triggers are worked on together, some at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        rows, want = 0, _ROWS
        for whole in batches:
            for x in range(0, whole.num_rows, _ROWS):
                batch = whole.slice(x, _ROWS)
                held.append(batch)
                rows += batch.num_rows
                if rows < want:
                    continue
                table = pa.Table.from_batches(held)
                trigger = np.asarray(table.column("trigger"))
                last = int(np.searchsorted(trigger, trigger[-1]))
                # one trigger alone is looked at again when it has grown to twice its rows
                want = _ROWS if last else 2 * rows
                if last:
                    yield work(table.slice(0, last), span, gram)
                    rest = table.slice(last)
                    held, rows = rest.to_batches(), rest.num_rows
        if rows:
            yield work(pa.Table.from_batches(held), span, gram)

    return run


def _cut_out(span: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in _unzipped(batches):
            alone, spans = batch.column("alone").to_pylist(), batch.column("spans").to_pylist()
            kept, removed = [], []
            for text, own, runs in zip(texts, alone, spans, strict=True):
                if not own and len(text) >= span:
                    runs = [{"a": 0, "b": len(text)}]
                merged: list[list[int]] = []
                for r in sorted(runs or [], key=lambda r: (r["a"], r["b"])):
                    if merged and r["a"] <= merged[-1][1]:
                        merged[-1][1] = max(merged[-1][1], r["b"])
                    else:
                        merged.append([r["a"], r["b"]])
                cuts = [0, *(x for pair in merged for x in pair), len(text)]
                kept.append(b"".join(text[cuts[i] : cuts[i + 1]] for i in range(0, len(cuts), 2)))
                removed.append([{"a": a, "b": b} for a, b in merged])
            less = pa.array([sum(p["b"] - p["a"] for p in m) for m in removed], pa.int64())
            shape = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
            yield pa.RecordBatch.from_arrays([batch.column("rest"), batch.column("n_bytes"), less, pa.array(removed, shape), pa.array(kept, pa.binary())], ["rest", "n_bytes", "n_removed", "spans", "kept"])

    return run


def _removed(docs: DataFrame, span: int, gram: int, hot: int) -> DataFrame:
    """rest (all columns without text), n_bytes, n_removed, spans and kept of each row."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rest = F.struct(F.lit(0).alias("__none"), *[docs[quoted(c)] for c in docs.columns if c != "text"])
    named = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(SMALLEST)).alias("id"), F.xxhash64(text).alias("told"), text.alias("text"), rest.alias("rest"))
    kind = named.schema["rest"]
    base = map_arrow(named, _zip(["id", "told", "rest"]), StructType([StructField("id", LongType()), StructField("told", LongType()), kind, StructField("packed", BinaryType()), StructField("n_bytes", LongType())]))
    # inner joins would add this filter to their copy of the plan only, and the texts would move twice
    base = base.filter(F.col("id").isNotNull() & F.col("told").isNotNull())
    owners = named.select("id", "told", F.md5("text").alias("digest")).groupBy("told", "digest").agg(F.min("id").alias("id"))
    # texts that share a doc_id are numbered; the number is 0 nearly everywhere
    owners = owners.select(F.col("id").alias("own_id"), F.col("told").alias("own_told"), (F.row_number().over(Window.partitionBy("id").orderBy("told", "digest")) - 1).alias("twin"))
    # every join is by id alone (other conditions are no equalities), so that one move of the texts serves all
    mine = (F.col("id") == F.col("own_id")) & (F.col("told") >= F.col("own_told")) & (F.col("told") <= F.col("own_told"))
    own = base.join(owners.hint("shuffle_hash"), mine).drop("own_id", "own_told")
    group = Window.partitionBy("trigger")
    # two columns and no more: these rows are the most that the operator moves
    triggers = map_arrow(own, _triggers(span, gram), "trigger long, id long")
    met = triggers.withColumns({"least": F.min("id").over(group), "most": F.max("id").over(group), "n": F.count(F.lit(1)).over(group)}).filter("least < most")
    shared = met.groupBy("id").agg(F.collect_list(F.when(F.col("n") <= hot, F.col("trigger"))).alias("cold"), F.collect_list(F.when(F.col("n") > hot, F.col("trigger"))).alias("hot")).hint("shuffle_hash")
    marked = own.join(shared, "id")
    parsed = "trigger long, phrase binary, before int, id long, twin int, starts array<bigint>"
    cold = map_arrow(marked.filter(F.size("cold") > 0).withColumn("triggers", F.col("cold")).drop("cold", "hot"), _phrases(span, gram), parsed)
    runs = map_arrow(cold.repartition("trigger").sortWithinPartitions("trigger"), _by_trigger(span, gram, _resolved), "id long, twin int, a long, b long")
    runs = runs.select("id", "twin", F.array(F.struct("a", "b")).alias("spans"))
    often = map_arrow(marked.filter(F.size("hot") > 0).withColumn("triggers", F.col("hot")).drop("cold", "hot"), _phrases(span, gram), parsed).withColumn("name", F.xxhash64("before", "phrase"))
    dictionary = often.groupBy("trigger", "name", "before", "phrase").agg(F.min("id").alias("low"))
    ordered = map_arrow(dictionary.repartition("trigger").sortWithinPartitions("trigger"), _by_trigger(span, gram, _ordered), "trigger long, name long, low long, spans array<struct<a:bigint,b:bigint>>")
    places = often.select("trigger", "name", "id", "twin", "starts", (F.octet_length("phrase") + gram).cast("long").alias("size")).join(ordered, ["trigger", "name"])
    whole = F.array(F.struct(F.lit(0).cast("long").alias("a"), F.col("size").alias("b")))
    inside = F.when(F.col("id") > F.col("low"), whole).otherwise(F.col("spans"))
    placed = places.withColumn("inside", inside).filter(F.size("inside") > 0)
    placed = placed.select("id", "twin", F.flatten(F.transform("starts", lambda s: F.transform("inside", lambda p: F.struct((p["a"] + s).alias("a"), (p["b"] + s).alias("b"))))).alias("spans"))
    runs = runs.unionByName(placed).groupBy("id", "twin").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    runs = runs.groupBy("id").agg(F.collect_list(F.struct("twin", "spans")).alias("by_twin")).hint("shuffle_hash")
    joined = base.join(owners.hint("shuffle_hash"), mine, "left").join(runs, "id", "left")
    spans = F.get(F.filter("by_twin", lambda t: t["twin"] == F.col("twin"))["spans"], F.lit(0))
    joined = joined.select("packed", "n_bytes", "rest", F.col("own_id").isNotNull().alias("alone"), spans.alias("spans"))
    pair = StructType([StructField("a", LongType()), StructField("b", LongType())])
    return map_arrow(joined, _cut_out(span), StructType([kind, StructField("n_bytes", LongType()), StructField("n_removed", LongType()), StructField("spans", ArrayType(pair)), StructField("kept", BinaryType())]))


def remove_repeats(docs: DataFrame, span: int = SPAN, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """The documents' columns without text, and n_bytes, n_removed, spans (removed, from-to) and kept (bytes)."""
    own = ("n_bytes", "n_removed", "spans", "kept")
    found = _removed(docs, span, gram, hot)
    return found.select(*[F.col("rest")[c].alias(c) for c in docs.columns if c != "text" and c not in own], *own)


def strip_repeats(docs: DataFrame, span: int = SPAN, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """The documents, their columns of any name, without repeated bytes; a character that lost a byte goes with it.

    ``n_chars``, if there is one, follows the text; a null text becomes empty.
    """
    found = _removed(docs, span, gram, hot)
    text = F.try_validate_utf8("kept")
    mended = F.when(F.col("n_removed") == 0, F.col("kept").cast("string")).when(text.isNotNull(), text).otherwise(F.replace(F.make_valid_utf8("kept"), F.lit("\ufffd"), F.lit("")))
    named = {"text": mended, "n_chars": F.length(mended).cast("long")}
    return found.select(*[named.get(c, F.col("rest")[c]).alias(c) for c in docs.columns])
