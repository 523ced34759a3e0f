"""Language identification by cross-parsing entropy.

Each language has a suffix automaton of a bounded labelled sample (at most ``SAMPLE_DOCUMENTS`` documents and
``SAMPLE_LETTERS`` letters). A text is parsed from left to right into phrases, each the longest match in the
automaton; the language whose phrases, times the logarithm of its sample's length, are fewest wins. Texts are
reduced to lower-case letters with single spaces. The texts of a slice are parsed together, one letter a step, in all
languages at once; when fewer than ``LANES`` texts are left, the rest of each is parsed alone. Every letter of the
samples has its number, in any script; letters that no sample has share one. Automata of at most ``DENSE_CELLS``
states times letters are a table, larger ones (thousands of letters) a sorted list of their transitions.

Defined cases: null texts and texts without a letter are ``und`` with score 0; ties go to the language first
in order; with no labelled text every document is ``und``; repeated rows are answered each; an empty
table gives no rows; null doc_ids stay (they count as held in); other columns are ignored, or kept as they are by
``keep_identified``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from sparkcurate.functions.arrow import kept, map_arrow
from sparkcurate.llm.native import quoted
from sparkcurate.llm.textscan import slices

SAMPLE_DOCUMENTS = 64
SAMPLE_LETTERS = 20_000
# texts that are parsed together at least, and the bytes of text of a slice
LANES = 24
PARSED_BYTES = 4 << 20
# characters that are read, and letters that are parsed alone, at once
_CHARACTERS = 1 << 20
UNKNOWN = "und"
DENSE_CELLS = 1 << 24
# code points above are looked up once for each distinct one
_TABLE = 0x3000
_SPACE, _OTHER = 1, 2


@lru_cache(maxsize=1)
def _lower_table() -> np.ndarray:
    """Lower-case code point of each letter below _TABLE, 32 for all others."""
    table = np.full(_TABLE, 32, np.int32)
    for c in range(_TABLE):
        if chr(c).isalpha():
            low = chr(c).lower()
            table[c] = ord(low) if len(low) == 1 else c
    return table


def _spaced(text: str) -> np.ndarray:
    """Code points of the text's letters in lower case; each run of others is one space, at the ends too."""
    points = np.frombuffer(text.encode("utf-32-le"), np.int32)
    table = _lower_table()
    low = table[np.minimum(points, _TABLE - 1)]
    high = np.flatnonzero(points >= _TABLE)
    if len(high):
        distinct, at = np.unique(points[high], return_inverse=True)
        lowered = [chr(c).lower() if chr(c).isalpha() else " " for c in distinct.tolist()]
        low[high] = np.array([ord(x) if len(x) == 1 else c for c, x in zip(distinct.tolist(), lowered, strict=True)], np.int32)[at]
    space = low == 32
    keep = np.ones(len(low), bool)
    keep[1:] = ~space[1:] | ~space[:-1]
    return low[keep]


def letters(text: str, code=lambda low: low) -> np.ndarray:
    """The same, without spaces at the ends, read some characters at a time; ``code`` is applied to each part."""
    parts, last, size = [code(np.zeros(0, np.int32))], 32, 0
    for x in range(0, len(text), _CHARACTERS):
        low = _spaced(text[x : x + _CHARACTERS])
        if len(low) and last == 32 and low[0] == 32:
            low = low[1:]
        if len(low):
            last = int(low[-1])
            size += len(low)
            parts.append(code(low))
    whole = np.concatenate(parts)
    return whole[:-1] if size and last == 32 else whole


class Transitions:
    """Sorted transitions, read like a table: state * symbols + symbol -> state * symbols, or -1."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        order = np.argsort(keys)
        self.keys, self.values = keys[order], values[order]
        self.one = dict(zip(self.keys.tolist(), self.values.tolist(), strict=True))

    def __getitem__(self, asked: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(asked.shape, -1, np.int64)
        at = np.minimum(np.searchsorted(self.keys, asked), len(self.keys) - 1)
        return np.where(self.keys[at] == asked, self.values[at], -1)


def suffix_automaton(sequence: list[int]) -> list[dict[int, int]]:
    """Transitions (symbol -> state) of each state of the sequence's suffix automaton; state 0 is the root."""
    follow: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in sequence:
        now = len(follow)
        follow.append({})
        length.append(length[last] + 1)
        link.append(0)
        at = last
        while at >= 0 and c not in follow[at]:
            follow[at][c] = now
            at = link[at]
        if at >= 0:
            to = follow[at][c]
            if length[at] + 1 == length[to]:
                link[now] = to
            else:
                copy = len(follow)
                follow.append(dict(follow[to]))
                length.append(length[at] + 1)
                link.append(link[to])
                while at >= 0 and follow[at].get(c) == to:
                    follow[at][c] = copy
                    at = link[at]
                link[to] = link[now] = copy
        last = now
    return follow


class CrossParser:
    def __init__(self, samples: tuple[tuple[str, str], ...], dense_cells: int = DENSE_CELLS):
        self.languages = [name for name, _ in samples]
        texts = [letters(t)[:SAMPLE_LETTERS] for _, t in samples]
        alphabet = np.unique(np.concatenate([*texts, [32]]))
        # 1 is the space, 2 any letter that no sample has
        self.symbols = len(alphabet) + 2
        self.kind = np.uint8 if self.symbols <= 256 else np.int32
        # the space is the least of the alphabet
        ranks = np.where(alphabet == 32, _SPACE, np.arange(len(alphabet)) + 2).astype(self.kind)
        below = alphabet < _TABLE
        self.numbers = np.full(_TABLE, _OTHER, self.kind)
        self.numbers[alphabet[below]] = ranks[below]
        self.high, self.high_numbers = alphabet[~below], ranks[~below]
        self.weight = np.array([np.log2(max(len(t), 2)) for t in texts])
        self._join([suffix_automaton(self.encode(t).tolist()) for t in texts], dense_cells)

    def _join(self, automata: list[list[dict[int, int]]], dense_cells: int) -> None:
        """All languages in one table: the states of each lie behind those of the one before; a state's number is its row's start."""
        sizes = np.array([len(a) for a in automata], np.int64)
        self.roots = (np.cumsum(sizes) - sizes) * self.symbols
        cells = int(sizes.sum()) * self.symbols
        made = np.array([(root + s * self.symbols + c, root + to * self.symbols) for root, a in zip(self.roots.tolist(), automata, strict=True) for s, row in enumerate(a) for c, to in row.items()], np.int64).reshape(-1, 2)
        if cells <= dense_cells:
            self.table = np.full(cells, -1, np.int32)
            self.table[made[:, 0]] = made[:, 1]
        else:
            self.table = Transitions(made[:, 0], made[:, 1])
        kind = np.int32 if cells <= dense_cells else np.int64
        self.roots = self.roots.astype(kind)
        begun = self.table[self.roots[:, None] + np.arange(self.symbols, dtype=kind)]
        # a letter that starts no phrase of its own is one
        self.alone = begun < 0
        self.first = np.where(self.alone, self.roots[:, None], begun).astype(kind)

    def encode(self, low: np.ndarray) -> np.ndarray:
        out = self.numbers[np.minimum(low, _TABLE - 1)]
        above = np.flatnonzero(low >= _TABLE)
        if len(above):
            out[above] = _OTHER
        if len(above) and len(self.high):
            at = np.minimum(np.searchsorted(self.high, low[above]), len(self.high) - 1)
            out[above] = np.where(self.high[at] == low[above], self.high_numbers[at], _OTHER)
        return out

    def phrases(self, coded: list[np.ndarray], lanes: int = LANES) -> np.ndarray:
        """Phrases of each text in each language."""
        size = np.array([len(c) for c in coded], np.int64)
        order = np.argsort(-size, kind="stable")
        # texts by falling length, so those that go on are always the first
        flat = np.concatenate([coded[i] for i in order.tolist()])
        size = size[order]
        start = np.cumsum(size) - size
        roots, languages = self.roots, len(self.roots)
        count = np.zeros((len(coded), languages), np.int32)
        state = np.repeat(roots[None, :], len(coded), axis=0)
        going = len(size) - np.searchsorted(size[::-1], np.arange(int(size[min(lanes, len(size)) - 1]) + 1), "right")
        step = 0
        for step, n in enumerate(going.tolist()):  # noqa: B007
            if n < lanes:
                break
            row = flat[start[:n] + step]
            now = state[:n]
            to = self.table[now + row[:, None]]
            # where no phrase goes on, one ends, and its letter begins the next
            failed = np.flatnonzero(to < 0)
            if len(failed):
                text, language = np.divmod(failed, languages)
                letter = row[text]
                count.reshape(-1)[failed] += (now.reshape(-1)[failed] != roots[language]).view(np.int8) + self.alone[language, letter].view(np.int8)
                to.reshape(-1)[failed] = self.first[language, letter]
            state[:n] = to
        for i in range(int((size > step).sum())):
            for x in range(int(start[i]) + step, int(start[i] + size[i]), _CHARACTERS):
                self._alone(flat[x : min(x + _CHARACTERS, int(start[i] + size[i]))].tolist(), state[i], count[i])
        out = np.empty((len(coded), languages), np.int64)
        out[order] = count + (state != roots)
        return out

    def _alone(self, codes: list[int], state: np.ndarray, count: np.ndarray) -> None:
        get = self.table.one.get if isinstance(self.table, Transitions) else None
        cells = None if get else memoryview(self.table)
        for k, root in enumerate(self.roots.tolist()):
            first, alone = self.first[k].tolist(), self.alone[k].tolist()
            at, n = int(state[k]), 0
            for c in codes:
                to = get(at + c, -1) if get else cells[at + c]
                if to < 0:
                    n += (at != root) + alone[c]
                    to = first[c]
                at = to
            state[k] = at
            count[k] += n

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
        coded = [letters(t, self.encode) if t else np.zeros(0, self.kind) for t in texts]
        some = [i for i, c in enumerate(coded) if len(c)]
        if not some or not self.languages:
            return names, scores
        sizes = np.array([len(coded[i]) for i in some], np.int64)
        entropy = self.phrases([coded[i] for i in some]) * self.weight / sizes[:, None]
        best = entropy.argmin(axis=1)
        ranked = np.sort(entropy, axis=1)
        second = ranked[:, 1] if ranked.shape[1] > 1 else ranked[:, 0] * 2 + 1
        for i, row in enumerate(some):
            names[row] = self.languages[best[i]]
            scores[row] = float(min(1.0, max(0.0, 1 - ranked[i, 0] / second[i]))) if second[i] > 0 else 0.0
        return names, scores


def _predict(samples: tuple[tuple[str, str], ...], column: str = "text"):
    """Adds lang_pred and score; a plain text column goes, one inside a struct stays."""
    outer, _, inner = column.partition(".")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parser = kept(CrossParser, samples)
        for batch in slices(batches, column, PARSED_BYTES):
            text = batch.column(outer).field(inner) if inner else batch.column(outer)
            names, scores = parser.predict(text.to_pylist())
            others = [c for c in batch.schema.names if inner or c != outer]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in others), pa.array(names, pa.string()), pa.array(scores, pa.float64())], [*others, "lang_pred", "score"])

    return run


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts == part, F.lit(False))


def learn_samples(docs: DataFrame) -> tuple[tuple[str, str], ...]:
    """Per language, the text of the bounded sample (documents in the order of a hash of their id).

    Only ids and hashes are ranked; the texts of the at most SAMPLE_DOCUMENTS chosen ones a language follow.
    """
    known = docs.filter(F.col("lang").isNotNull() & F.col("text").rlike(r"\p{L}")).select("lang", F.xxhash64(F.col("doc_id").cast("string")).alias("told"), F.xxhash64("text").alias("digest"), "text")
    order = Window.partitionBy("lang").orderBy("told", "digest")
    chosen = known.select("lang", "told", "digest").withColumn("place", F.row_number().over(order)).filter(F.col("place") <= SAMPLE_DOCUMENTS)
    # equal rows have equal texts, so any of them serves for a place
    found = known.join(F.broadcast(chosen), ["lang", "told", "digest"]).groupBy("lang", "place").agg(F.min(F.substring("text", 1, 8 * SAMPLE_LETTERS)).alias("text"))
    samples: dict[str, str] = {}
    for r in found.orderBy("lang", "place").collect():
        have = samples.setdefault(r["lang"], "")
        if len(have) < 2 * SAMPLE_LETTERS:
            samples[r["lang"]] = have + r["text"] + "\n"
    return tuple((k, v[: 2 * SAMPLE_LETTERS]) for k, v in sorted(samples.items()))


def identify_languages(docs: DataFrame, learned_from: DataFrame | None = None, parts: int = 3, part: int = 1) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row; learns from the rows that are not held out."""
    source = docs if learned_from is None else learned_from
    samples = learn_samples(source.filter(~held_out(F.col("doc_id"), parts, part)))
    asked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), parts, part).alias("held_out"), F.col("text").cast("string").alias("text"))
    return map_arrow(asked, _predict(samples), "doc_id long, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame) -> DataFrame:
    """The documents with a known language, which is written into ``lang``; columns of any name stay."""
    samples = learn_samples(docs.filter(~held_out(F.col("doc_id"), 3, 1)))
    rest = docs.select(F.struct(*[docs[quoted(c)].cast("string").alias(c) if c == "text" else docs[quoted(c)] for c in docs.columns]).alias("rest"))
    found = map_arrow(rest, _predict(samples, "rest.text"), StructType([*rest.schema.fields, StructField("lang_pred", StringType()), StructField("score", DoubleType())]))
    return found.filter(F.col("lang_pred") != UNKNOWN).select(*[F.col("lang_pred").alias(c) if c == "lang" else F.col("rest")[c].alias(c) for c in docs.columns])
