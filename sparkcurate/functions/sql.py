"""Functions registered for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from sparkcurate.functions.arrow import ship_package


class NGrams:
    """ngrams(text, n): one row (pos, gram) an n-gram of the text's tokens."""

    def eval(self, text: str, n: int):
        import re

        words = [w for w in re.split(r"[\W_]+", (text or "").lower()) if w]
        for i in range(len(words) - n + 1):
            yield i, " ".join(words[i : i + n])


def register(spark: SparkSession) -> None:
    ship_package(spark)
    spark.udtf.register("ngrams", udtf(NGrams, returnType="pos int, gram string"))
