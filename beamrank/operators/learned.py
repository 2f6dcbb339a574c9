"""Learned verifiers and selectors: linear models over hashed or plain features.

They stand in for fine-tuned encoders and heads, and show how training sets and orders matter.
"""

from __future__ import annotations

import math

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, NGram, RegexTokenizer, VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def text_verifier(train: DataFrame, text: str = "text", label: str = "label", buckets: int = 1 << 14):
    """Hashed one- and two-word counts, and a logistic regression."""
    steps = [
        RegexTokenizer(inputCol=text, outputCol="tokens", pattern="\\s+"),
        NGram(n=2, inputCol="tokens", outputCol="pairs"),
        HashingTF(inputCol="tokens", outputCol="one", numFeatures=buckets),
        HashingTF(inputCol="pairs", outputCol="two", numFeatures=buckets),
        VectorAssembler(inputCols=["one", "two"], outputCol="features"),
        LogisticRegression(labelCol=label, maxIter=20, regParam=0.05),
    ]
    return Pipeline(stages=steps).fit(train)


def probability(model, df: DataFrame, name: str = "prob") -> DataFrame:
    return model.transform(df).withColumn(name, vector_to_array("probability")[1])


def item_model(train: DataFrame, features: list[str], label: str = "correct"):
    """A scorer of single candidates from numbers."""
    rows = train.withColumn("label", F.col(label).cast("double"))
    steps = [VectorAssembler(inputCols=features, outputCol="features"), LogisticRegression(labelCol="label", maxIter=30)]
    return Pipeline(stages=steps).fit(rows)


def select_by_model(model, df: DataFrame, pos: str = "pos") -> DataFrame:
    """The candidate with the largest probability in each beam; of equal ones the first."""
    rank = Window.partitionBy("beam_id").orderBy(F.desc(F.round("prob", 9)), pos)
    return probability(model, df).withColumn("r", F.row_number().over(rank)).where("r = 1").select("beam_id", "item_id", "correct")


def two_stage(stages: list[tuple[str, DataFrame]], features: list[str], label: str, steps: int = 15, rate: float = 2.0) -> list[tuple[str, int, float]]:
    """Gradient descent on one set after another, each starting from the weights of the one before.

    A step is one aggregate: the gradient is a few sums. Returns (stage, step, mean loss before it).
    """
    weights, losses = [0.0] * (len(features) + 1), []
    for name, df in stages:
        df = df.select(*[F.col(f).cast("double").alias(f) for f in features], F.col(label).cast("double").alias("y"))
        for step in range(steps):
            margin: Column = F.lit(weights[-1])
            for w, f in zip(weights, features, strict=False):
                margin = margin + F.lit(w) * F.col(f)
            p = 1 / (1 + F.exp(-margin))
            miss = p - F.col("y")
            loss = -(F.col("y") * F.log(p) + (1 - F.col("y")) * F.log(1 - p))
            row = df.agg(*[F.avg(miss * F.col(f)).alias(f) for f in features], F.avg(miss).alias("bias"), F.avg(loss).alias("loss")).head()
            losses.append((name, step, math.floor(row["loss"] * 1e6) / 1e6))
            weights = [w - rate * row[f] for w, f in zip(weights, [*features, "bias"], strict=True)]
    return losses
