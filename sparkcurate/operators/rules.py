"""Row-local rules: language, completeness, format, heuristics, labels.

Defined cases, for all rules here: null texts count as empty, so they are incomplete, of no language and without
keywords; null labels are kept by no filter on labels; ties between languages and domains go to the first named; equal
rows are judged alike; an empty table gives no rows; other columns pass through.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.text import STOP_WORDS, domain_of_source, tokens

MAX_TOKENS = 32_768


def filter_language(df: DataFrame, keep: tuple[str, ...] = ("en",), col: str = "lang") -> DataFrame:
    return df.filter(F.col(col).isin(*keep))


def detect_language(text: Column, lexicons: dict[str, list[str]] | None = None) -> Column:
    """The language with most distinct stop words in the text (first of equals); null if there is none."""
    lexicons = lexicons or STOP_WORDS
    found = tokens(text)
    hits = {k: F.size(F.array_intersect(found, F.array(*[F.lit(w) for w in v]))) for k, v in lexicons.items()}
    best = F.greatest(*hits.values())
    out = F.when(best == 0, F.lit(None).cast("string"))
    for k, h in hits.items():
        out = out.when(h == best, k)
    return out


def is_complete(text: Column, min_tokens: int = 5) -> Column:
    """Not blank, long enough, and closed by a full stop, exclamation or question mark."""
    body = F.trim(F.coalesce(text, F.lit("")))
    return (F.size(tokens(text)) >= min_tokens) & body.rlike(r"[.!?]$")


def filter_complete(df: DataFrame, text_col: str = "text", min_tokens: int = 5) -> DataFrame:
    return df.filter(is_complete(F.col(text_col), min_tokens))


def missing_traces(pairs: DataFrame) -> DataFrame:
    return pairs.filter(F.col("response").isNull())


def format_reasons(response: Column, domain: Column, max_tokens: int = MAX_TOKENS) -> Column:
    """Why a response fails the format checks; empty if it passes."""
    body = F.coalesce(response, F.lit(""))
    return F.array_compact(F.array(
        F.when(F.trim(body) == "", "empty"),
        F.when(~body.rlike(r"[.!?}`]\s*$"), "incomplete"),
        F.when(F.size(tokens(body)) > max_tokens, "too_long"),
        F.when((domain == "math") & ~F.contains(body, F.lit("\\boxed{")), "no_boxed_answer"),
        F.when((domain == "code") & ~F.contains(body, F.lit("```")), "no_program"),
    ))


def heuristic_scores(text: Column) -> dict[str, Column]:
    """Stand-ins of a judge: variety of tokens, share of repeated lines, share of signs."""
    body = F.coalesce(text, F.lit(""))
    words, lines = tokens(text), F.split(body, "\n")
    return {
        "variety": F.when(F.size(words) > 0, F.round(F.size(F.array_distinct(words)) / F.size(words), 6)).otherwise(0.0),
        "repeated_lines": F.round(1 - F.size(F.array_distinct(lines)) / F.size(lines), 6),
        "signs": F.when(F.length(body) > 0, F.round(F.length(F.regexp_replace(body, r"[\p{L}\p{N}\s]", "")) / F.length(body), 6)).otherwise(0.0),
    }


def filter_judged(df: DataFrame, text_col: str = "text", min_variety: float = 0.3, max_repeated: float = 0.3, max_signs: float = 0.15) -> DataFrame:
    scores = heuristic_scores(F.col(text_col))
    return df.filter((scores["variety"] >= min_variety) & (scores["repeated_lines"] <= max_repeated) & (scores["signs"] <= max_signs))


def filter_keywords(df: DataFrame, words: tuple[str, ...], text_col: str = "text") -> DataFrame:
    """Fixed keyword rule: a record with one of the words goes."""
    return df.filter(~F.arrays_overlap(tokens(F.col(text_col)), F.array(*[F.lit(w) for w in words])))


# Frequent words of three domains, a small stand-in for a classifier's knowledge.
DOMAIN_WORDS = {
    "math": ["number", "equation", "theorem", "proof", "sum", "triangle", "integral", "prove"],
    "code": ["function", "program", "code", "python", "array", "string", "return", "algorithm"],
    "science": ["energy", "cell", "force", "reaction", "molecule", "species", "temperature", "atom"],
}


def lexicon_domain(text: Column, lexicon: dict[str, list[str]] | None = None, default: str | None = None) -> Column:
    """The domain with most occurrences of its words in the text (first of equals); the default if there is none."""
    found = tokens(text)
    words = {k: F.array(*[F.lit(w) for w in v]) for k, v in (lexicon or DOMAIN_WORDS).items()}
    hits = {k: F.size(F.filter(found, partial(F.array_contains, v))) for k, v in words.items()}
    best = F.greatest(*hits.values(), F.lit(0))
    out = F.when(best == 0, F.lit(default))
    for k, h in hits.items():
        out = out.when(h == best, k)
    return out


def annotate_domain(df: DataFrame, classifier: str = "source_mod", col: str = "source", lexicon: dict[str, list[str]] | None = None, default: str | None = None) -> DataFrame:
    """Adds domain and category: by the source's number (``source_mod``), from a column (``column``), or by the words of a text column (``lexicon``).

    A model's labels come from ``quality.annotate_with``.
    """
    if classifier == "lexicon":
        found = lexicon_domain(F.col(col), lexicon, default)
        return df.withColumn("domain", found).withColumn("category", F.col("domain"))
    if classifier == "source_mod":
        return df.withColumn("domain", domain_of_source(F.col(col))).withColumn("category", F.col(col))
    if classifier == "column":
        return df.withColumn("domain", F.col(col)).withColumn("category", F.col(col))
    raise ValueError(f"unknown classifier {classifier}")


def annotate_taxonomy(df: DataFrame, taxonomy: DataFrame, key: str = "source") -> DataFrame:
    """Two-level labels of a taxonomy table (domain, category, keyed by source); flat domains keep their name as category."""
    wide = df.join(F.broadcast(taxonomy), key, "left")
    return wide.withColumn("category", F.coalesce("category", "domain"))
