"""Packing token pieces into windows by Karmarkar-Karp multiway differencing.

A document's ids (closed by an end id) are cut at multiples of the window; full windows stand alone and
only the tails are packed. Equal pieces are counted before they move, and each copy is dealt by its hash and number
into a group of about ``GROUP`` pieces of its kind (full or tail), so no group grows with the input or with one
row's copies. In a group, every tail starts as a partition with one filled window; the two
partitions with the largest imbalance are merged again and again, the fullest window of one meeting the
emptiest of the other, until one near-equal partition is left. The window count starts at the least
possible and rises while the fullest window exceeds the capacity.

Words between ASCII white space are encoded once a worker and remembered (at most ``REMEMBERED`` of
them); the tokenizer drops white space, so a text's ids are those of its words in turn. A text that holds the
literal of a special token, in any case, is encoded whole.

Defined cases: null and empty texts have the end id alone; repeated rows are packed each; an empty table
gives no rows; null doc_ids are packed like others; other columns are ignored.
"""

from __future__ import annotations

import heapq
import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import kept, map_arrow, ship_package
from sparkcurate.functions.lineage import cut
from sparkcurate.llm.textscan import slices

WINDOW = 4096
END_ID = 2
GROUP = 2000
REMEMBERED = 1_000_000
# marks that are split off behind a letter
MARKS = b".,;:!?"
_SEQUENCES_BITS = 32
# bytes of text that are encoded together: words that recur among them are looked up once
PACKED_BYTES = 2 << 20
# small letters of A-Z and of Latin above ASCII without the dotted I, and perhaps a mark behind them
_PLAIN = re.compile(rb"((?:[a-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf]|\xc4[\x80-\xaf\xb1-\xbf]|[\xc5-\xc8][\x80-\xbf])+)[.,;:!?]?").fullmatch


def partition(sizes: np.ndarray, windows: int) -> np.ndarray:
    """Window of each item under multiway differencing; ties are settled by item order."""
    n = len(sizes)
    if windows == 1:
        return np.zeros(n, np.int64)
    sums: list[np.ndarray | None] = []
    heap: list[tuple[int, int]] = []
    for i, s in enumerate(sizes.tolist()):
        start = np.zeros(windows, np.int64)
        start[0] = s
        sums.append(start)
        heap.append((-s, i))
    heapq.heapify(heap)
    merges: list[tuple[int, int, np.ndarray]] = []
    while len(heap) > 1:
        _, a = heapq.heappop(heap)
        _, b = heapq.heappop(heap)
        # kept in falling order, so the fullest of one meets the emptiest of the other
        joined = sums[a] + sums[b][::-1]
        order = np.argsort(-joined, kind="stable")
        joined = joined[order]
        joined -= joined[-1]
        sums[a] = sums[b] = None
        merges.append((a, b, order.astype(np.int32)))
        sums.append(joined)
        heapq.heappush(heap, (-int(joined[0]), len(sums) - 1))
    slot: dict[int, np.ndarray] = {len(sums) - 1: np.arange(windows, dtype=np.int32)}
    for k in range(len(merges) - 1, -1, -1):
        a, b, order = merges[k]
        mine = slot.pop(n + k)
        where = np.empty(windows, np.int32)
        where[order] = mine
        slot[a], slot[b] = where, where[::-1]
    return np.array([slot[i][0] for i in range(n)], np.int64)


def pack(sizes: np.ndarray, capacity: int) -> np.ndarray:
    """Windows 0, 1, ... of the items; none above the capacity."""
    if not len(sizes):
        return np.zeros(0, np.int64)
    windows = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        found = partition(sizes, windows)
        if np.bincount(found, weights=sizes).max() <= capacity:
            return np.unique(found, return_inverse=True)[1]
        windows += 1


class WordEncoder:
    """Ids (little-endian bytes) of texts by a tokenizer file whose pre-tokens never hold white space."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content.lower().encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.known: dict[bytes, bytes] = {}
        vocabulary = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)
        for token, i in vocabulary.items():
            self.closes[i] = token.endswith("</w>")
        self.marks = {bytes([m]): np.array(self.tokenizer.encode(chr(m), add_special_tokens=False).ids, "<u4").tobytes() for m in MARKS}

    def _encode(self, words: list[str]) -> Iterator[bytes]:
        encode = getattr(self.tokenizer, "encode_batch_fast", self.tokenizer.encode_batch)
        for found in encode(words, add_special_tokens=False):
            yield np.array(found.ids, "<u4").tobytes()

    def _learn(self, words: list[bytes]) -> None:
        """Words of plain letters are encoded in one text and told apart by their closing tokens, others alone."""
        plain: dict[bytes, None] = {}
        alone: dict[bytes, str] = {}
        marked: list[tuple[bytes, bytes]] = []
        for word in words:
            if found := _PLAIN(word):
                core = found[1]
                if core != word:
                    marked.append((word, core))
                    if core in self.known:
                        continue
                plain[core] = None
                continue
            core, mark = (word[:-1], word[-1:]) if word[-1:] in self.marks else (word, b"")
            text = core.decode()
            # a mark is a pre-token of its own behind a letter only, and a dotted I is lower-cased to a letter and a dot
            if not (text and text[-1].isalpha() and text[-1] < "\u0250" and text[-1] != "\u0130"):
                core, mark, text = word, b"", word.decode()
            if mark:
                marked.append((word, core))
                if core in self.known:
                    continue
            alone[core] = text
        cores = list(plain)
        for x in range(0, len(cores), 5000):
            some = cores[x : x + 5000]
            ids = np.array(self.tokenizer.encode(b" ".join(some).decode(), add_special_tokens=False).ids, "<u4")
            ends = np.flatnonzero(self.closes[ids]) + 1
            if len(ends) == len(some):
                data, at = ids.tobytes(), [0, *(4 * ends).tolist()]
                for c, a, b in zip(some, at, at[1:], strict=False):
                    self.known[c] = data[a:b]
            else:
                alone.update((c, c.decode()) for c in some)
        for core, ids in zip(alone, self._encode(list(alone.values())), strict=True):
            self.known[core] = ids
        for word, core in marked:
            self.known[word] = self.known[core] + self.marks[word[-1:]]

    def __call__(self, texts: list[bytes]) -> Iterator[bytes]:
        # the tokenizer lower-cases, so ASCII capitals need no entry of their own, but for those that may be composed with a mark
        parts = [t.lower() for t in texts]
        whole = [any(literal in t for literal in self.special) for t in parts]
        parts = [[] if w else (t if b"\xcc" in t or b"\xcd" in t else low).split() for t, low, w in zip(texts, parts, whole, strict=True)]
        words = set().union(*parts)
        known = self.known
        # looked up word by word: a difference of sets would go through all that is remembered
        new = [w for w in words if w not in known]
        if len(known) + len(new) > REMEMBERED:
            known.clear()
            new = list(words)
        self._learn(new)
        get = self.known.__getitem__
        for text, own, is_whole in zip(texts, parts, whole, strict=True):
            yield next(self._encode([text.decode()])) if is_whole else b"".join(map(get, own))


def _encoder(path: str) -> WordEncoder:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    return kept(WordEncoder, path)


def _pieces(path: str, window: int, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(path)
        end = np.array([end_id], "<u4").tobytes()
        for batch in slices(batches, size=PACKED_BYTES):
            texts = pa.compute.fill_null(batch.column("text"), "").cast(pa.binary()).to_pylist()
            row, start, length, crc, total = [], [], [], [], []
            for i, ids in enumerate(encode(texts)):
                ids += end
                n = len(ids) // 4
                for a in range(0, n, window):
                    piece = ids[4 * a : 4 * (a + window)]
                    row.append(i)
                    start.append(a)
                    length.append(len(piece) // 4)
                    crc.append(zlib.crc32(piece))
                    total.append(n)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(row, pa.int64())), *(pa.array(c, pa.int64()) for c in (start, length, crc, total))], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return run


def _pack_group(window: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["length", "doc_id", "start", "ids_crc32"], ascending=[False, True, True, True], kind="stable").reset_index(drop=True)
        sequence = np.zeros(len(rows), np.int64)
        full = int((rows["length"] == window).sum())
        sequence[:full] = np.arange(full)
        used = full
        sequence[full:] = full + pack(rows["length"].to_numpy()[full:], window)
        rows["sequence_id"] = (rows["pack"].to_numpy(np.int64) << _SEQUENCES_BITS) + sequence
        rows = rows.sort_values(["sequence_id", "doc_id", "start"], kind="stable")
        rows["offset"] = rows.groupby("sequence_id")["length"].cumsum() - rows["length"]
        return rows[["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]]

    return run


def pack_documents(docs: DataFrame, tokenizer: str, window: int = WINDOW, end_id: int = END_ID, group: int = GROUP) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    ship_package(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    piece = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    pieces = map_arrow(texts, _pieces(tokenizer, window, end_id), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")
    counted = cut(pieces.groupBy(*piece).agg(F.count(F.lit(1)).alias("copies")))
    full = F.col("length") == window
    n_full, n_tails = counted.select(F.sum(F.when(full, F.col("copies"))), F.sum(F.when(~full, F.col("copies")))).first()
    copies = counted.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    hashed = F.xxhash64("doc_id", "start", "ids_crc32", "copy")
    groups = [max(1, -(-(n or 0) // group)) for n in (n_full, n_tails)]
    # groups of full windows have even numbers, those of tails odd ones
    dealt = copies.withColumn("pack", F.when(full, 2 * F.pmod(hashed, F.lit(groups[0]))).otherwise(2 * F.pmod(hashed, F.lit(groups[1])) + 1))
    return dealt.groupBy("pack").applyInPandas(_pack_group(window), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
