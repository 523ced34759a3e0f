"""Text expressions: tokens, n-grams, seeded order, lexicons."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SEPARATORS = r"[^\p{L}\p{N}]+"

# Frequent words that tell four languages apart.
STOP_WORDS = {
    "en": ["the", "of", "and", "to", "in", "is", "that", "it"],
    "fr": ["le", "la", "les", "et", "des", "est", "une", "dans"],
    "de": ["der", "die", "das", "und", "ist", "nicht", "ein", "mit"],
    "es": ["el", "los", "las", "y", "que", "del", "una", "por"],
}

# Discourse markers by family.
MARKERS = {
    "reflection": ["wait", "hmm", "let me check", "on second thought"],
    "branching": ["alternatively", "on the other hand", "another way"],
    "conclusion": ["therefore", "so", "thus", "in conclusion", "and the"],
}


def tokens(text: Column) -> Column:
    """Lower-cased Unicode word tokens; null text has none."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda w: w != "")


def n_tokens(text: Column) -> Column:
    return F.size(tokens(text)).cast("long")


def bound(value: Column, use) -> Column:
    """use(value) with the value worked out once, however often it is used."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def gram_hashes(token_array: Column, n: int) -> Column:
    """64-bit hashes of all n-grams of a token array (none if it is shorter).

    Each word is hashed once; hashes of twice the width come from two neighbours, so a gram costs about two
    steps for each doubling of n and not n word hashes. A null array has no grams.
    """

    def joined(left: Column, right: Column, shift: int) -> Column:
        # the last ones lack a right neighbour and are cut off in the end
        return F.zip_with(left, F.slice(right, shift + 1, F.greatest(F.size(right) - shift, F.lit(0))), lambda a, b: F.xxhash64(a, b))

    def grow(power: Column, width: int, done: Column | None, done_width: int) -> Column:
        if n & width:
            whole = power if done is None else joined(done, power, done_width)
            if done_width + width == n:
                return whole
            if done is None:
                return bound(joined(power, power, width), lambda p: grow(p, 2 * width, power, width))
            return bound(whole, lambda w: bound(joined(power, power, width), lambda p: grow(p, 2 * width, w, done_width + width)))
        return bound(joined(power, power, width), lambda p: grow(p, 2 * width, done, done_width))

    hashed = F.transform(token_array, lambda w: F.xxhash64(w))
    count = F.greatest(F.size(token_array) - (n - 1), F.lit(0))
    return F.when(count > 0, F.slice(bound(hashed, lambda h: grow(h, 1, None, 0)), 1, count)).otherwise(F.array().cast("array<bigint>"))


def grams(df: DataFrame, id_col: str, text_col: str, n: int) -> DataFrame:
    """Distinct (id, gram) rows."""
    words = df.select(F.col(id_col), tokens(F.col(text_col)).alias("__t"))
    return words.select(id_col, F.explode(F.array_distinct(gram_hashes(F.col("__t"), n))).alias("gram"))


def seeded(id_col: str | Column, seed: int = 42) -> Column:
    """The order of a random draw: stable over partitions and engines."""
    column = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.md5(F.concat_ws(":", F.lit(str(seed)), column.cast("string")))


def hex_number(digest: Column, start: int, length: int) -> Column:
    """Number in the hexadecimal digits of a digest."""
    return F.conv(F.substring(digest, start, length), 16, 10).cast("long")


def source_number(source: Column) -> Column:
    return F.regexp_extract(source, r"(\d+)$", 1).cast("int")


def domain_of_source(source: Column) -> Column:
    """Stand-in for a model's label: the source's number modulo three."""
    number = source_number(source) % 3
    return F.when(number == 0, "math").when(number == 1, "code").when(number == 2, "science")


def leading_sentence(text: Column) -> Column:
    return F.regexp_extract(text, r"^([^.!?\n]+[.!?]?)", 1)


def marker_counts(text: Column, lexicon: dict[str, list[str]]) -> dict[str, Column]:
    """Occurrences of each family's phrases as whole words."""
    low = F.lower(F.coalesce(text, F.lit("")))
    return {family: sum((F.regexp_count(low, F.lit(rf"\b{p}\b")) for p in phrases[1:]), F.regexp_count(low, F.lit(rf"\b{phrases[0]}\b"))).cast("long") for family, phrases in lexicon.items()}
