"""Token counts of sections by offset-mapped attribution.

A whole document is encoded once. Tokens carry byte spans (their lengths come from the vocabulary), as do
sections; both lists are sorted and gapless, so the interval join is a binary search. A token inside
one section counts there. A token that crosses a boundary is allocated by an explicit rule:

- ``start``: to the section of its first byte;
- ``majority``: to the section with most of its bytes (the earlier one, if equal);
- ``share``: to each section by its share of the token's bytes.

Sections are lines, each with its closing newline; other sections can be given as a function from
the text's bytes to their sorted starts.

Defined cases: null and empty texts have one empty section without tokens; repeated rows are counted
each; an empty table gives no rows; null doc_ids stay; other columns are ignored. Runs of ``LONG`` white space
characters or more, which the tokenizer's pattern matcher has no stack for, are cut off at the places where that
pattern cuts and encoded as the one piece that they are.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.llm.textscan import slices, text_bytes

RULES = ("start", "majority", "share")
LONG = 1000
# The characters that the pattern's class of white space has, and the pattern's alternatives for it.
_LONG_SPACE = re.compile(rf"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{{{LONG},}}")
_SPACE_RULE = r"|\s+(?!\S)|\s+"


class RankEncoder:
    """A byte-level vocabulary of ranks, with the byte length of every token."""

    def __init__(self, path: str, pattern: str):
        import tiktoken

        with open(path, "rb") as file:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}
        self.encoding = tiktoken.Encoding("offsets", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.cuts_space = pattern.endswith(_SPACE_RULE)
        self.size = np.zeros(max(ranks.values()) + 1, np.int64)
        for token, rank in ranks.items():
            self.size[rank] = len(token)

    def ranks(self, text: str) -> list[int]:
        found: list[int] = []
        at = 0
        for run in _LONG_SPACE.finditer(text) if self.cuts_space else ():
            # all but the last character of a run are one piece; the last goes with what follows
            end = run.end() if run.end() == len(text) else run.end() - 1
            found += self.encoding.encode_ordinary(text[at : run.start()])
            found += self.encoding._encode_single_piece(text[run.start() : end].encode())
            at = end
        return found + self.encoding.encode_ordinary(text[at:])

    def ends(self, text: str) -> np.ndarray:
        """End of each token in bytes."""
        return np.cumsum(self.size[np.asarray(self.ranks(text), np.int64)])


@lru_cache(maxsize=2)
def _encoder(path: str, pattern: str) -> RankEncoder:
    return RankEncoder(path, pattern)


def line_starts(data: np.ndarray) -> np.ndarray:
    """Starts of the lines of a text."""
    after = np.flatnonzero(data == 10) + 1
    return np.concatenate([[0], after[after < len(data)]])


def attribute(ends: np.ndarray, bounds: np.ndarray) -> dict[str, np.ndarray]:
    """Counts of sections (bounds has their starts and the text's end) for tokens that end at ``ends``."""
    sections = len(bounds) - 1
    starts = np.concatenate([[0], ends[:-1]]) if len(ends) else ends
    first = np.searchsorted(bounds, starts, "right") - 1
    last = np.searchsorted(bounds, ends - 1, "right") - 1
    crossing = np.flatnonzero(last > first)
    inside = np.bincount(np.delete(first, crossing), minlength=sections)
    by_start = np.bincount(first, minlength=sections)
    majority, share, crossed = inside.copy(), inside.astype(np.float64), np.zeros(sections, np.int64)
    for t in crossing.tolist():
        at = np.arange(first[t], last[t] + 1)
        held = np.minimum(bounds[at + 1], ends[t]) - np.maximum(bounds[at], starts[t])
        majority[at[np.argmax(held)]] += 1
        share[at] += held / held.sum()
        crossed[at] += 1
    return {"start": by_start, "majority": majority, "share": share, "crossing": crossed}


def _count(path: str, pattern: str, sections: Callable[[np.ndarray], np.ndarray]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(path, pattern)
        for batch in slices(batches):
            data, offsets = text_bytes(batch.column("text"))
            texts = batch.column("text").to_pylist()
            parts: dict[str, list[np.ndarray]] = {c: [] for c in ("row", "section", "start_char", "end_char", *RULES, "crossing")}
            for i, text in enumerate(texts):
                own = data[offsets[i] : offsets[i + 1]]
                bounds = np.append(sections(own), len(own)).astype(np.int64)
                found = attribute(encoder.ends(text or ""), bounds)
                chars = np.concatenate([[0], np.cumsum((own & 0xC0) != 0x80)])[bounds]
                n = len(bounds) - 1
                for c, v in {"row": np.full(n, i), "section": np.arange(n), "start_char": chars[:-1], "end_char": chars[1:], **found}.items():
                    parts[c].append(v)
            whole = {c: np.concatenate(v) for c, v in parts.items()}
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(whole["row"])), *(pa.array(whole[c].astype(np.int64)) for c in ("section", "start_char", "end_char", "start", "majority")), pa.array(np.round(whole["share"], 6)), pa.array(whole["crossing"])],
                ["doc_id", "section", "start_char", "end_char", "tokens_start", "tokens_majority", "tokens_share", "n_crossing"],
            )

    return run


def section_tokens(docs: DataFrame, vocabulary: str, pattern: str, sections: Callable[[np.ndarray], np.ndarray] = line_starts) -> DataFrame:
    """One row a section: its place in characters, its tokens by each rule, and the tokens that cross its bounds."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_arrow(texts, _count(vocabulary, pattern, sections), "doc_id long, section long, start_char long, end_char long, tokens_start long, tokens_majority long, tokens_share double, n_crossing long")
