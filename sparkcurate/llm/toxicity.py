"""Toxicity by gradient-boosted trees over dense features, calibrated by isotonic regression.

Features are computed from the whole text alone: densities of two lexicons, insults near second-person words,
second-person words, capitals, shouted words, punctuation, signs and digits. One lexicon is given (insults, plain
and written with digits or signs for letters), the other is learned: words and word beginnings (``STEMS`` bytes)
that more toxic than clean texts of a bounded labelled sample (``SAMPLE_ROWS``) hold, weighed by the lower bound
of their log-odds, at most ``LEXICON`` of them. A training row's learned densities come from the other folds'
labels only. Trees are boosted on the logistic loss over binned features; margins of trees that have not
seen a row (``FOLDS`` folds) calibrate them by pooling adjacent violators. Scoring is row-local.

Defined cases: null and empty texts have all-zero features and get the score of such texts; without any
label of both kinds the score is the share of toxic labels (0 if there are none); of documents that share a
labelled doc_id one is learned from (that with the least text hash); a doc_id with both labels is toxic;
repeated rows are scored each; an empty table gives no rows; null doc_ids stay (they count as held in); other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import map_arrow
from sparkcurate.functions.lineage import cut
from sparkcurate.llm.language_id import held_out
from sparkcurate.llm.textscan import LOWERED, U, Words, distinct_by_row, mix, prefix_hash, slices, span_hash, text_bytes

SAMPLE_ROWS = 20_000
BINS = 48
TREES = 40
DEPTH = 3
RATE = 0.2
SHRINK = 1.0
LEAST_WEIGHT = 0.4
LEAST_GAIN = 2.0
FOLDS = 4
NEAR = 6
CUT = 0.3
# lengths in bytes of the word beginnings that are learned, besides whole words
STEMS = (3, 4, 5, 6, 7, 8)
LEXICON = 50_000
LEAST_TOXIC = 3
LEAST_ODDS = 1.0

# Insults and second-person words in English, French, German and Spanish, and the signs
# that are written for letters.
INSULTS = (
    "idiot idiots idiotic moron morons moronic stupid dumb fool fools loser losers pathetic trash garbage scum filth vermin worthless disgusting clown clowns jerk imbecile "
    "creep pig pigs liar coward freak bastard bitch shit fuck fucking crap asshole dickhead retard shut ugly hate "
    "idiote imbécile crétin connard salaud ordure débile pathétique nul minable "
    "idiotisch dumm dumme trottel arschloch abschaum dreckig widerlich versager "
    "idiota estúpido estúpida imbécil basura patético inútil asqueroso tonto payaso"
).split()
SECOND_PERSON = "you your yours yourself u ur tu te toi vous votre du dich dein deine ihr euch usted ustedes vosotros".split()
LETTER_SIGNS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"}

FEATURES = (
    "log_words", "insult_density", "insult_count", "insult_kinds", "insult_peak", "disguised_density", "disguised_count", "second_density",
    "near_second", "capitals", "shouted", "punctuation", "exclamations", "signs", "digits", "repeats", "word_length",
    "learned_density", "learned_top", "learned_second", "learned_count", "learned_proof",
)


def _hashes(words: list[str]) -> np.ndarray:
    data, offsets = text_bytes(pa.array([" ".join(words)]))
    return np.unique(Words(data, offsets).hash)


def _member(hashes: np.ndarray, known: np.ndarray) -> np.ndarray:
    return known[np.minimum(np.searchsorted(known, hashes), len(known) - 1)] == hashes


@dataclass
class Lexicon:
    """Learned stems (sorted hashes) with their weights and the strength of their proof."""

    stems: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    weight: np.ndarray = field(default_factory=lambda: np.zeros(0))
    proof: np.ndarray = field(default_factory=lambda: np.zeros(0))

    @classmethod
    def learned(cls, stems: np.ndarray, toxic: np.ndarray, clean: np.ndarray, n_toxic: int, n_clean: int) -> Lexicon:
        """From the numbers of toxic and clean texts that hold each stem."""
        odds = np.log((toxic + 0.5) / (n_toxic - toxic + 0.5)) - np.log((clean + 0.5) / (n_clean - clean + 0.5))
        weight = odds - np.sqrt(1 / (toxic + 0.5) + 1 / (clean + 0.5))
        both, share = toxic + clean, n_toxic / max(n_toxic + n_clean, 1)
        proof = toxic * np.log(np.maximum(toxic, 1e-9) / np.maximum(both * share, 1e-9)) + clean * np.log(np.maximum(clean, 1e-9) / np.maximum(both * (1 - share), 1e-9))
        keep = np.flatnonzero((toxic >= LEAST_TOXIC) & (weight >= LEAST_ODDS))
        keep = keep[np.argsort(stems[keep])]
        return cls(stems[keep], weight[keep], proof[keep])

    def densities(self, words: Words, low: np.ndarray, n: int) -> list[np.ndarray]:
        """The learned features of n texts: weight a word, largest and second weight, words with one, largest proof."""
        best, proof = np.zeros(len(words.hash)), np.zeros(len(words.hash))
        if len(self.stems):
            for places, hashes in stems_of(words, low):
                at = np.minimum(np.searchsorted(self.stems, hashes), len(self.stems) - 1)
                known = self.stems[at] == hashes
                places, at = places[known], at[known]
                best[places] = np.maximum(best[places], self.weight[at])
                proof[places] = np.maximum(proof[places], self.proof[at])
        top, second, strongest = np.zeros(n), np.zeros(n), np.zeros(n)
        some = np.flatnonzero(best)
        row = words.row[some]
        order = np.lexsort((-best[some], row))
        row, value = row[order], best[some][order]
        first = np.ones(len(row), bool)
        first[1:] = row[1:] != row[:-1]
        top[row[first]] = value[first]
        after = np.flatnonzero(first) + 1
        after = after[after < len(row)]
        after = after[~first[after]]
        second[row[after]] = value[after]
        np.maximum.at(strongest, words.row, proof)
        return [np.bincount(words.row, best, n) / np.maximum(words.count, 1), top, second, np.minimum(np.bincount(row, minlength=n), 50), strongest]


def stems_of(words: Words, low: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(numbers of words, hashes) of the whole words, then of the words' beginnings of each length in STEMS."""
    yield np.arange(len(words.hash)), words.hash
    prefix = prefix_hash(low)
    size = words.ends - words.starts
    for n in STEMS:
        some = np.flatnonzero(size > n)
        yield some, mix(span_hash(prefix, words.starts[some], words.starts[some] + n) + U(n))


def features(column: pa.Array, lexicon: Lexicon) -> np.ndarray:
    """One row of FEATURES a text."""
    data, offsets = text_bytes(column)
    n = len(offsets) - 1
    sizes = np.diff(offsets)
    per_byte = 1 / np.maximum(sizes, 1)
    insults, second = _hashes(INSULTS), _hashes(SECOND_PERSON)
    words = Words(data, offsets)
    per_word = 1 / np.maximum(words.count, 1)
    rows = lambda mask: np.bincount(words.row[mask], minlength=n)

    def share(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask)])
        return (total[offsets[1:]] - total[offsets[:-1]]) * per_byte

    insult = _member(words.hash, insults)
    at = np.flatnonzero(insult)
    kinds = np.zeros(n)
    if len(at):
        kind = np.unique(np.stack([words.row[at], np.searchsorted(insults, words.hash[at])]), axis=1)
        kinds = np.bincount(kind[0], minlength=n)
    peak = np.zeros(n)
    if len(at):
        same = np.searchsorted(at, at + 50)
        crowd = np.minimum(same, np.searchsorted(words.row[at], words.row[at], "right")) - np.arange(len(at))
        np.maximum.at(peak, words.row[at], crowd)
    you = _member(words.hash, second)
    around = np.concatenate([[0], np.cumsum(you)])
    low, high = np.maximum(at - NEAR, words.first[words.row[at]]), np.minimum(at + NEAR + 1, words.first[words.row[at] + 1])
    near = np.bincount(words.row[at], weights=(around[high] - around[low]) > 0, minlength=n)
    # the same text with signs read as letters
    plain = LOWERED.copy()
    signs = np.zeros(256, bool)
    for sign, letter in LETTER_SIGNS.items():
        plain[ord(sign)] = ord(letter)
        signs[ord(sign)] = True
    if len(data):
        read = Words(plain[data], offsets)
        swapped = np.concatenate([[0], np.cumsum(signs[data])])
        changed = swapped[read.ends] > swapped[read.starts]
        disguised = np.bincount(read.row[changed & _member(read.hash, insults)], minlength=n)
    else:
        disguised = np.zeros(n)
    upper = (data >= 65) & (data <= 90)
    capitals = np.concatenate([[0], np.cumsum(upper)])
    long_words = words.ends - words.starts
    shouted = (long_words > 2) & (capitals[words.ends] - capitals[words.starts] == long_words)
    mark = ((data > 32) & (data < 48)) | ((data > 57) & (data < 65)) | ((data > 90) & (data < 97)) | ((data > 122) & (data < 127))
    special = np.isin(data, np.frombuffer(b"#$%&*@^~_|<>+=", np.uint8))
    repeat = np.zeros(len(data), bool)
    repeat[2:] = (data[2:] == data[1:-1]) & (data[1:-1] == data[:-2]) & (data[2:] > 32)
    count = rows(insult)
    table = [
        np.log1p(words.count), count * per_word, np.minimum(count, 20), kinds, peak, disguised * per_word, np.minimum(disguised, 20), rows(you) * per_word,
        near, share(upper), rows(shouted) * per_word, share(mark), share(data == 33), share(special), share((data >= 48) & (data <= 57)), share(repeat),
        np.bincount(words.row, weights=long_words, minlength=n) * per_word, *lexicon.densities(words, LOWERED[data], n),
    ]
    return np.stack([np.asarray(c, np.float64) for c in table], axis=1)


@dataclass
class BoostedTrees:
    """Trees of fixed depth over binned features; nodes in level order."""

    edges: list[np.ndarray] = field(default_factory=list)
    base: float = 0.0
    column: list[np.ndarray] = field(default_factory=list)
    split: list[np.ndarray] = field(default_factory=list)
    leaf: list[np.ndarray] = field(default_factory=list)

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(self.edges)], axis=1).astype(np.int16) if len(x) else np.zeros(x.shape, np.int16)

    def margin(self, x: np.ndarray) -> np.ndarray:
        binned, out = self.bins(x), np.full(len(x), self.base)
        each = np.arange(len(x))
        for column, split, leaf in zip(self.column, self.split, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(DEPTH):
                node = 2 * node + 1 + (binned[each, column[node]] > split[node])
            out += leaf[node - (2**DEPTH - 1)]
        return out

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        self.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS)[1:-1])) for j in range(x.shape[1])]
        binned = self.bins(x).astype(np.int64)
        rate = min(max(y.mean(), 1e-6), 1 - 1e-6)
        self.base = float(np.log(rate / (1 - rate)))
        score = np.full(len(y), self.base)
        inner = 2**DEPTH - 1
        for _ in range(TREES):
            chance = 1 / (1 + np.exp(-score))
            slope, weight = y - chance, chance * (1 - chance)
            column, split = np.zeros(inner, np.int64), np.full(inner, BINS + 1)
            node = np.zeros(len(y), np.int64)
            for level in range(DEPTH):
                start, width = 2**level - 1, 2**level
                place = node - start
                best = np.full(width, LEAST_GAIN)
                for j in range(x.shape[1]):
                    cell = place * (BINS + 1) + binned[:, j]
                    g = np.cumsum(np.bincount(cell, slope, width * (BINS + 1)).reshape(width, -1), axis=1)
                    h = np.cumsum(np.bincount(cell, weight, width * (BINS + 1)).reshape(width, -1), axis=1)
                    gt, ht = g[:, -1:], h[:, -1:]
                    gain = g**2 / (h + SHRINK) + (gt - g) ** 2 / (ht - h + SHRINK) - gt**2 / (ht + SHRINK)
                    gain[(h < LEAST_WEIGHT) | (ht - h < LEAST_WEIGHT)] = 0
                    at = gain.argmax(axis=1)
                    top = gain[np.arange(width), at]
                    better = top > best
                    best[better] = top[better]
                    column[start : start + width][better], split[start : start + width][better] = j, at[better]
                node = 2 * node + 1 + (binned[np.arange(len(y)), column[node]] > split[node])
            place = node - inner
            leaf = RATE * np.bincount(place, slope, inner + 1) / (np.bincount(place, weight, inner + 1) + SHRINK)
            score += leaf[place]
            self.column.append(column)
            self.split.append(split)
            self.leaf.append(leaf)
        return self


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Knots of the non-decreasing fit by pooling adjacent violators; equal x are one point."""
    if not len(x):
        return np.zeros(1), np.zeros(1)
    at, inverse, weight = np.unique(x, return_inverse=True, return_counts=True)
    mean = np.bincount(inverse, y) / weight
    blocks: list[list[float]] = []
    for k, (m, w) in enumerate(zip(mean.tolist(), weight.tolist(), strict=True)):
        blocks.append([m, w, k, k])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            m2, w2, _, b = blocks.pop()
            m1, w1, a, _ = blocks.pop()
            blocks.append([(m1 * w1 + m2 * w2) / (w1 + w2), w1 + w2, a, b])
    xs, ys = [], []
    for m, _, a, b in blocks:
        xs += [at[int(a)], at[int(b)]]
        ys += [m, m]
    return np.array(xs), np.array(ys)


@dataclass
class ToxicityModel:
    trees: BoostedTrees | None
    knots: tuple[np.ndarray, np.ndarray]
    lexicon: Lexicon = field(default_factory=Lexicon)

    def score(self, x: np.ndarray) -> np.ndarray:
        margin = self.trees.margin(x) if self.trees else np.zeros(len(x))
        # the slight slope keeps the order of margins inside a calibrated step
        return np.clip(0.999 * np.interp(margin, *self.knots) + 0.001 / (1 + np.exp(-margin)), 0, 1)


def fit_model(x: np.ndarray, y: np.ndarray, fold: np.ndarray, lexicon: Lexicon) -> ToxicityModel:
    if len(y) < 2 * FOLDS or any(len(np.unique(y[fold != k])) < 2 for k in range(FOLDS)):
        return ToxicityModel(None, (np.zeros(1), np.full(1, float(y.mean()) if len(y) else 0.0)))
    margin = np.zeros(len(y))
    for k in np.unique(fold).tolist():
        margin[fold == k] = BoostedTrees().fit(x[fold != k], y[fold != k]).margin(x[fold == k])
    return ToxicityModel(BoostedTrees().fit(x, y), isotonic(margin, y), lexicon)


def _distinct_stems(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(fold, toxic, stem), once for each text that holds the stem."""
    for batch in slices(batches):
        data, offsets = text_bytes(batch.column("text"))
        low = LOWERED[data]
        words = Words(data, offsets)
        found = [(words.row[places], hashes) for places, hashes in stems_of(words, low)] if len(data) else []
        if found:
            stems, rows = distinct_by_row(np.concatenate([h for _, h in found]), np.concatenate([r for r, _ in found]))
            at = pa.array(rows)
            yield pa.RecordBatch.from_arrays([batch.column("fold").take(at), batch.column("toxic").take(at), pa.array(stems.view(np.int64))], ["fold", "toxic", "stem"])


def learn_lexicons(texts: DataFrame, sizes: np.ndarray) -> tuple[list[Lexicon], Lexicon]:
    """For each fold the lexicon of the other folds, and that of all; sizes has the clean and toxic texts of each fold."""
    each = map_arrow(texts.select("fold", "toxic", "text"), _distinct_stems, "fold int, toxic int, stem long")
    counts = [F.count(F.when((F.col("fold") == k) & (F.col("toxic") == t), 1)).alias(f"n{k}{t}") for k in range(FOLDS) for t in (0, 1)]
    met = each.groupBy("stem").agg(*counts)
    toxic = sum((F.col(f"n{k}1") for k in range(1, FOLDS)), F.col("n01"))
    clean = sum((F.col(f"n{k}0") for k in range(1, FOLDS)), F.col("n00"))
    share = int(sizes[:, 1].sum()) / max(int(sizes.sum()), 1)
    # stems more frequent in toxic texts than overall, the most telling first
    kept = met.filter((toxic >= LEAST_TOXIC) & (toxic > 2 * share * (toxic + clean))).orderBy(F.desc(toxic / (clean + 1)), "stem").limit(LEXICON).toPandas()
    stems = kept["stem"].to_numpy(np.int64).view(np.uint64)
    n = kept.drop(columns="stem").to_numpy(np.int64).reshape(len(kept), FOLDS, 2)

    def without(k: int | None) -> Lexicon:
        rest = [f for f in range(FOLDS) if f != k]
        return Lexicon.learned(stems, n[:, rest, 1].sum(axis=1), n[:, rest, 0].sum(axis=1), int(sizes[rest, 1].sum()), int(sizes[rest, 0].sum()))

    return [without(k) for k in range(FOLDS)], without(None)


def _features(lexicons: list[Lexicon]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            fold = np.asarray(batch.column("fold"))
            x = np.zeros((batch.num_rows, len(FEATURES)))
            for k in np.unique(fold).tolist():
                x[fold == k] = features(batch.column("text").filter(pa.array(fold == k)), lexicons[k])
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "toxic", "fold")), pa.array(x.tolist(), pa.list_(pa.float64()))], ["doc_id", "toxic", "fold", "features"])

    return run


def learn(docs: DataFrame, labels: DataFrame, parts: int = 4, part: int = 2, rows: int = SAMPLE_ROWS) -> ToxicityModel:
    """Model of at most ``rows`` labelled documents that are not held out, taken in the order of a hash of their id."""
    known = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), parts, part)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic"))
    known = known.groupBy("doc_id").agg((F.max("toxic") > 0).cast("int").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    met = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).join(F.broadcast(known), "doc_id")
    texts = cut(met.groupBy("doc_id", "toxic").agg(F.min_by("text", F.xxhash64("text")).alias("text")).withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit("fold")), F.lit(FOLDS)).cast("int")))
    sizes = np.zeros((FOLDS, 2), np.int64)
    for r in texts.groupBy("fold", "toxic").count().collect():
        sizes[r["fold"], r["toxic"]] = r["count"]
    lexicons, whole = learn_lexicons(texts, sizes)
    got = map_arrow(texts, _features(lexicons), "doc_id long, toxic int, fold int, features array<double>").toPandas().sort_values("doc_id", kind="stable")
    x = np.array(got["features"].tolist(), np.float64).reshape(-1, len(FEATURES))
    return fit_model(x, got["toxic"].to_numpy(np.float64), got["fold"].to_numpy(np.int64), whole)


def _score(model: ToxicityModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            score = model.score(features(batch.column("text"), model.lexicon))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(score), pa.array((score >= CUT).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return run


def score_toxicity(docs: DataFrame, labels: DataFrame, parts: int = 4, part: int = 2) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    model = learn(docs, labels, parts, part)
    asked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), parts, part).alias("held_out"), F.col("text").cast("string").alias("text"))
    return map_arrow(asked, _score(model), "doc_id long, held_out boolean, score double, predicted int")
