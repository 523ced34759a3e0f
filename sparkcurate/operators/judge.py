"""Learned stand-in of a judge: TF-IDF and logistic regression on quality labels, with a held-out split."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.text import hex_number, seeded, tokens
from sparkcurate.operators.evaluate import auc

SAMPLE = 50_000


def train_quality_model(docs: DataFrame, labels: DataFrame, features: int = 4096):
    """Fitted on at most SAMPLE labelled documents that are not held out."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import IDF, HashingTF

    known = labels.filter(F.col("quality").isNotNull()).select("doc_id", "quality").filter(~held_out("doc_id")).orderBy(seeded("doc_id")).limit(SAMPLE)
    rows = docs.select("doc_id", tokens(F.col("text")).alias("words")).join(known, "doc_id").select("words", F.col("quality").cast("double").alias("label"))
    steps = [HashingTF(inputCol="words", outputCol="tf", numFeatures=features), IDF(inputCol="tf", outputCol="features"), LogisticRegression(maxIter=10, regParam=0.1)]
    return Pipeline(stages=steps).fit(rows)


def held_out(key: str):
    return hex_number(seeded(key, 7), 1, 1) < 4


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Area under the curve of the model on the held-out labels."""
    from pyspark.ml.functions import vector_to_array

    model = train_quality_model(docs, labels)
    asked = docs.select("doc_id", tokens(F.col("text")).alias("words")).join(labels.filter(held_out("doc_id")).select("doc_id", "quality"), "doc_id")
    scored = model.transform(asked).select("quality", F.get(vector_to_array("probability"), F.lit(1)).alias("score"))
    return auc(scored, "score", "quality")
