"""Vectorised text scanning for Arrow batches: bytes, words, word hashes and shingles in numpy.

Texts are read in place as UTF-8 bytes and worked on in slices of at most ``SLICE_BYTES`` (or one
text), so memory stays bounded by the slice and the longest text. Hashes are 64-bit: a polynomial over
random byte values, finished by a mixing step.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 1 << 19

U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)

LOWERED = np.arange(256, dtype=np.uint8)
LOWERED[65:91] += 32
IS_WORD = np.zeros(256, dtype=bool)
IS_WORD[48:58] = IS_WORD[65:91] = IS_WORD[97:123] = IS_WORD[128:] = True


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective finisher on 64 bits."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x = x * U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


BYTE_VALUES = mix(np.arange(1, 257, dtype=np.uint64) * U(0xD1342543DE82EF95))
_powers = {_BASE: np.ones(1, np.uint64), _INVERSE: np.ones(1, np.uint64)}


def powers(base: int, n: int) -> np.ndarray:
    if len(_powers[base]) < n:
        made = np.full(max(n, SLICE_BYTES + 1), base, np.uint64)
        made[0] = 1
        np.cumprod(made, out=made)
        if n > 4 * SLICE_BYTES:
            return made
        _powers[base] = made
    return _powers[base][:n]


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a text column and the offsets of its rows; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", size: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches again, cut so that each holds about ``size`` bytes of text or a single row; ``rest.text`` names a field."""
    outer, _, inner = column.partition(".")
    for batch in batches:
        text = batch.column(outer).field(inner) if inner else batch.column(outer)
        sizes = np.asarray(pc.fill_null(pc.binary_length(text), 0), np.int64)
        group = np.cumsum(sizes) // size
        cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b > a:
                yield batch.slice(a, b - a)


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """h with h[i] the hash sum of the first i bytes; see ``span_hash``."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_VALUES[data] * powers(_BASE, len(data)), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return mix((prefix[ends] - prefix[starts]) * powers(_INVERSE, len(prefix))[starts])


class Words:
    """Words of a slice: byte places, hashes and the row each belongs to."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        low = LOWERED[data]
        inside = IS_WORD[data]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        rows = offsets[:-1][offsets[:-1] < len(data)]
        first[rows] = inside[rows]
        last = inside.copy()
        last[:-1] &= ~inside[1:]
        ends = offsets[1:][offsets[1:] > 0] - 1
        last[ends] = inside[ends]
        self.starts = np.flatnonzero(first)
        self.ends = np.flatnonzero(last) + 1
        self.row = np.searchsorted(offsets, self.starts, "right") - 1
        self.hash = span_hash(prefix_hash(low), self.starts, self.ends)
        self.count = np.bincount(self.row, minlength=len(offsets) - 1)
        self.first = np.concatenate([[0], np.cumsum(self.count)])


def shingles(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash and row of each k-word shingle; a row of fewer words, but not none, has one of all its words."""
    m = max(len(words.hash) - k + 1, 0)
    total = np.zeros(m, np.uint64)
    for j in range(k):
        total = total * U(_BASE) + words.hash[j : j + m]
    whole = words.row[:m] == words.row[k - 1 : k - 1 + m]
    hashes, rows = mix(total[whole]), words.row[:m][whole]
    short = np.flatnonzero((words.count > 0) & (words.count < k))
    if len(short):
        extra = np.zeros(len(short), np.uint64)
        for x, r in enumerate(short.tolist()):
            h = 0
            for v in words.hash[words.first[r] : words.first[r + 1]].tolist():
                h = (h * _BASE + v + 1) & 0xFFFFFFFFFFFFFFFF
            extra[x] = h
        hashes, rows = np.concatenate([hashes, mix(extra)]), np.concatenate([rows, short])
        order = np.argsort(rows, kind="stable")
        hashes, rows = hashes[order], rows[order]
    return hashes, rows


def distinct_by_row(hashes: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (row, hash), sorted by both."""
    order = np.lexsort((hashes, rows))
    hashes, rows = hashes[order], rows[order]
    keep = np.ones(len(hashes), bool)
    keep[1:] = (hashes[1:] != hashes[:-1]) | (rows[1:] != rows[:-1])
    return hashes[keep], rows[keep]
