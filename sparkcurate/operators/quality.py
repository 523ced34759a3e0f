"""Verification, regeneration and judging behind pluggable model clients.

Defined cases, for all operators here: a null response is answered by ``distill``, fails every verifier and is judged
as an empty text; a null truth is never met; rows that share an id ask the same question; an empty table gives no
rows; other columns pass through. Clients and verifiers work on a batch and must be picklable.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from fractions import Fraction
from typing import Protocol

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import ship_package
from sparkcurate.functions.lineage import cut
from sparkcurate.functions.text import hex_number

MAX_ATTEMPTS = 8


class ModelClient(Protocol):
    """A batched model: calls carry (id, attempt), so repeated task attempts ask the same question again."""

    def complete(self, ids: list[str], prompts: list[str], attempt: int) -> list[str]: ...


class StubClient:
    """Deterministic stand-in for a model: the answer is a digest of the id and the attempt."""

    def complete(self, ids: list[str], prompts: list[str], attempt: int) -> list[str]:
        return ["stub:" + hashlib.md5(f"{i}:{attempt}".encode()).hexdigest() for i in ids]


def distill(pairs: DataFrame, client: ModelClient, key: str = "qid") -> DataFrame:
    """Missing responses from the client, a batch at a time; present ones are kept."""
    ship_package(pairs.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            gap = rows["response"].isna()
            if gap.any():
                rows = rows.copy()
                rows.loc[gap, "response"] = client.complete(rows.loc[gap, key].astype(str).tolist(), rows.loc[gap, "question"].tolist(), 1)
            yield rows

    return pairs.mapInPandas(run, pairs.schema)


def boxed_answer(text: str | None) -> str | None:
    """Content of the last closed \\boxed{...}, braces balanced."""
    found, at = None, 0
    body = text or ""
    while (at := body.find("\\boxed{", at)) >= 0:
        depth, start = 1, at + 7
        for i in range(start, len(body)):
            depth += (body[i] == "{") - (body[i] == "}")
            if depth == 0:
                found = body[start:i]
                break
        at = start
    return found


def normal_number(text: str | None) -> str | None:
    """Numbers and fractions in lowest terms, other answers without white space."""
    if text is None:
        return None
    bare = re.sub(r"\s+", "", text).replace(",", "").strip("$")
    bare = re.sub(r"\\[dt]?frac\{([^{}]+)\}\{([^{}]+)\}", r"\1/\2", bare)
    try:
        return str(Fraction(bare))
    except (ValueError, ZeroDivisionError):
        return bare


def verify_boxed(df: DataFrame, response: str = "response", truth: str = "truth") -> DataFrame:
    """Adds ``passed``: the boxed answer equals the truth after normalisation."""
    return verify(df, BoxedVerifier(), response, truth)


def last_program(text: str | None) -> str | None:
    """Content of the last closed fenced block, without its language mark."""
    found = re.findall(r"```[^\n`]*\n(.*?)```", text or "", re.DOTALL)
    return found[-1] if found else None


class Sandbox(Protocol):
    """Runs programs against their tests somewhere safe; nothing is executed in this process."""

    def run(self, programs: list[str], tests: list[str]) -> list[bool]: ...


class StubSandbox:
    """Deterministic stand-in: a program passes if it holds its test as a word."""

    def run(self, programs: list[str], tests: list[str]) -> list[bool]:
        return [bool(re.search(rf"\b{re.escape(t)}\b", p)) for p, t in zip(programs, tests, strict=True)]


class Verifier(Protocol):
    """Told (responses, truths) of a batch, returns whether each is right."""

    def __call__(self, responses: list[str | None], truths: list[str | None]) -> list[bool]: ...


class BoxedVerifier:
    """The boxed answer equals the truth after normalisation."""

    def __call__(self, responses, truths):
        return [(got := normal_number(boxed_answer(x))) is not None and got == normal_number(y) for x, y in zip(responses, truths, strict=True)]


class ProgramVerifier:
    """The last program of the response passes the truth's tests in a sandbox; a response without one fails."""

    def __init__(self, sandbox: Sandbox):
        self.sandbox = sandbox

    def __call__(self, responses, truths):
        programs = [last_program(x) for x in responses]
        asked = [i for i, (p, t) in enumerate(zip(programs, truths, strict=True)) if p is not None and t is not None]
        told = dict(zip(asked, self.sandbox.run([programs[i] for i in asked], [truths[i] for i in asked]), strict=True)) if asked else {}
        return [told.get(i, False) for i in range(len(programs))]


def verify(df: DataFrame, verifier: Verifier, response: str = "response", truth: str = "truth") -> DataFrame:
    """Adds ``passed`` by any verifier, a batch at a time."""
    ship_package(df.sparkSession)

    @F.pandas_udf("boolean")
    def told(a: pd.Series, b: pd.Series) -> pd.Series:
        clean = lambda s: [None if pd.isna(x) else x for x in s]
        return pd.Series(verifier(clean(a), clean(b)), dtype=bool)

    return df.withColumn("passed", told(F.col(response), F.col(truth)))


ASPECTS = ("clarity", "redundancy", "informativeness", "confidence")


class JudgeClient(Protocol):
    """Rates texts in each of ASPECTS from 0 to 1 (redundancy: lower is better)."""

    def rate(self, ids: list[str], texts: list[str]) -> list[tuple[float, ...]]: ...


class StubJudge:
    """Deterministic stand-in: two hexadecimal digits of a digest of the id and the aspect."""

    def rate(self, ids: list[str], texts: list[str]) -> list[tuple[float, ...]]:
        return [tuple(int(hashlib.md5(f"{i}:{a}".encode()).hexdigest()[:2], 16) / 255 for a in ASPECTS) for i in ids]


def judge(df: DataFrame, client: JudgeClient, key: str = "qid", text_col: str = "response") -> DataFrame:
    """(id, one column an aspect) from the client, a batch at a time."""
    ship_package(df.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            rated = client.rate(rows["key"].tolist(), rows["text"].tolist())
            yield pd.concat([rows[[key]].reset_index(drop=True), pd.DataFrame(rated, columns=list(ASPECTS), dtype=float)], axis=1)

    asked = df.select(key, F.col(key).cast("string").alias("key"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return asked.mapInPandas(run, f"{key} {df.schema[key].dataType.simpleString()}, " + ", ".join(f"{a} double" for a in ASPECTS))


def filter_by_judge(judged: DataFrame, least: float = 0.3, most_redundant: float = 0.7, confidence: float = 0.5) -> DataFrame:
    """Ratings that are good enough, of a judge that was sure enough; ambiguous ones go."""
    return judged.filter((F.col("clarity") >= least) & (F.col("informativeness") >= least) & (F.col("redundancy") <= most_redundant) & (F.col("confidence") >= confidence))


def annotate_with(df: DataFrame, client: ModelClient, labels: list[str], key: str = "qid", text_col: str = "question") -> DataFrame:
    """(id, domain, category) by a model that answers ``domain/category``; answers outside the labels are null."""
    ship_package(df.sparkSession)
    known = set(labels)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            told = [a.strip() if a.strip() in known else None for a in client.complete(rows["key"].tolist(), rows["text"].tolist(), 1)]
            split = [(a.partition("/")[0], a.partition("/")[2] or a) if a else (None, None) for a in told]
            yield pd.DataFrame({key: rows[key].tolist(), "domain": [a for a, _ in split], "category": [b for _, b in split]})

    asked = df.select(key, F.col(key).cast("string").alias("key"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return asked.mapInPandas(run, f"{key} {df.schema[key].dataType.simpleString()}, domain string, category string")


class StubLabels:
    """Deterministic stand-in for a classifier: a label drawn by a digest of the id."""

    def __init__(self, labels: list[str]):
        self.labels = labels

    def complete(self, ids: list[str], prompts: list[str], attempt: int) -> list[str]:
        return [self.labels[int(hashlib.md5(f"{i}:{attempt}".encode()).hexdigest()[:2], 16) % len(self.labels)] for i in ids]


def stub_passes(key: Column, attempt: Column, cut_off: int = 5) -> Column:
    """Stand-in verdict: a hexadecimal digit of a digest of id and attempt is below the cut."""
    return hex_number(F.md5(F.concat_ws(":", key.cast("string"), attempt.cast("string"))), 1, 1) < cut_off


def verify_regenerate_stub(df: DataFrame, key: str, max_attempts: int = MAX_ATTEMPTS, cut_off: int = 5) -> DataFrame:
    """(id, attempts, passed) of the loop under the stand-in verdict, as one expression a row."""
    tries = F.filter(F.sequence(F.lit(1), F.lit(max_attempts)), lambda a: stub_passes(F.col(key), a, cut_off))
    first = F.array_min(tries)
    return df.select(key, F.coalesce(first, F.lit(max_attempts)).alias("attempts"), first.isNotNull().alias("passed"))


def verify_regenerate(df: DataFrame, key: str, client: ModelClient, verifier, max_attempts: int = MAX_ATTEMPTS) -> DataFrame:
    """Verify, and regenerate what fails, up to ``max_attempts`` attempts; the loop runs inside a batch on the failing rows alone.

    ``verifier(ids, responses, attempt)`` returns booleans. Adds response, attempts and passed.
    """
    ship_package(df.sparkSession)
    columns = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            rows = rows.reset_index(drop=True).copy()
            ids = rows[key].astype(str)
            rows["attempts"], rows["passed"] = 0, False
            left = rows.index
            for attempt in range(1, max_attempts + 1):
                if attempt > 1:
                    rows.loc[left, "response"] = client.complete(ids[left].tolist(), rows.loc[left, "question"].tolist(), attempt)
                good = pd.Series(verifier(ids[left].tolist(), rows.loc[left, "response"].tolist(), attempt), index=left, dtype=bool)
                rows.loc[left, "attempts"] = attempt
                rows.loc[left[good], "passed"] = True
                left = left[~good]
                if not len(left):
                    break
            yield rows

    return df.mapInPandas(run, f"{columns}, attempts int, passed boolean")


def verify_regenerate_rounds(df: DataFrame, key: str, max_attempts: int = MAX_ATTEMPTS, cut_off: int = 5) -> DataFrame:
    """The loop as one checkpointed frame a round, for costly remote calls that must be restartable."""
    done: DataFrame | None = None
    left = df.select(key)
    for attempt in range(1, max_attempts + 1):
        tried = cut(left.withColumn("attempts", F.lit(attempt)).withColumn("passed", stub_passes(F.col(key), F.lit(attempt), cut_off)))
        over = tried if attempt == max_attempts else tried.filter("passed")
        done = over if done is None else done.unionByName(over)
        left = tried.filter(~F.col("passed")).select(key)
    return done


def route(df: DataFrame, domain: str = "domain") -> DataFrame:
    """Adds ``route``: verifiable domains go to verifiers, others to the judge."""
    return df.withColumn("route", F.when(F.col(domain).isin("math", "code"), "verify").otherwise("judge"))
