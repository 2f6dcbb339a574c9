"""Learned verifiers and selectors on the carriers."""

from __future__ import annotations

from itertools import product

from pyspark.sql import functions as F

from beamrank.operators import beams, learned, metrics
from beamrank.plans.registry import query
from beamrank.sources.tables import doc_beams, line_beams, table

FEATURES = ["score", "price_s", "rank_s"]


def _doc_scores(spark, d):
    docs = doc_beams(spark, d).where("correct is not null").join(table(spark, d, "documents").select(F.col("doc_id").alias("item_id"), F.coalesce("text", F.lit("")).alias("text")), "item_id")
    rows = docs.select("beam_id", "pos", "item_id", "correct", "text", F.col("correct").cast("double").alias("label"))
    model = learned.text_verifier(rows.where("item_id % 5 < 4"))
    return learned.probability(model, rows)


@query("verifier_scores")
def verifier_scores(spark, d):
    """Probabilities of a verifier learnt from four fifths of the labelled documents, for all of them."""
    return _doc_scores(spark, d).select("item_id", (F.col("item_id") % 5 == 4).alias("held_out"), "correct", F.round("prob", 6).alias("prob"))


@query("verifier_learned_prf")
def verifier_learned_prf(spark, d):
    rows = _doc_scores(spark, d).withColumn("held_out", F.col("item_id") % 5 == 4).withColumn("verified", F.col("prob") >= 0.5)
    return metrics.prf(rows, "held_out")


def _scaled(rows):
    return rows.select("beam_id", "pos", "item_id", "correct", (F.col("score") / 50).alias("score"), (F.col("price") / 100_000).alias("price_s"))


def _items(spark, d, k):
    rows = beams.first_k(beams.with_gold(line_beams(spark, d)), k)
    return _scaled(rows.withColumn("correct", F.col("correct") | (F.col("pos") == F.col("gold_pos"))))


def _training_items(spark, d, k):
    return _scaled(beams.with_gold_first(line_beams(spark, d), k).where("beam_id % 5 < 4"))


def _select(spark, d, k: int, order: str, origin: int | None = None):
    """Accuracy on held-out beams of a selector trained on reordered ones."""
    train = _training_items(spark, d, k)
    if origin is not None:
        train = train.where(F.col("beam_id") % 2 == origin)
    moved = beams.reorder_random(train) if order == "random" else beams.reorder_geometric(train, k)
    model = learned.item_model(moved.withColumn("rank_s", F.col("new_pos") / k), FEATURES)
    return learned.select_by_model(model, _items(spark, d, k).where("beam_id % 5 = 4").withColumn("rank_s", F.col("pos") / k))


@query("selector5")
def selector5(spark, d):
    return metrics.accuracy(_select(spark, d, 5, "geometric"))


@query("selector2")
def selector2(spark, d):
    return metrics.accuracy(_select(spark, d, 2, "geometric"))


@query("selector_grid")
def selector_grid(spark, d):
    """Random and geometric orders, five and two candidates, beams of two origins: eight fits."""
    out = None
    for order, k, origin in product(("random", "geometric"), (5, 2), (0, 1)):
        row = metrics.accuracy(_select(spark, d, k, order, origin)).select(F.lit(order).alias("order"), F.lit(k).alias("k"), F.lit(("alg", "seq")[origin]).alias("origin"), "accuracy")
        out = row if out is None else out.union(row)
    return out


@query("two_stage_train")
def two_stage_train(spark, d):
    """Noisy labels of synthetic make first, then the gold ones, from where the first left off."""
    rows = _items(spark, d, 5).withColumn("rank_s", F.col("pos") / 5)
    noisy = rows.withColumn("y", F.when(beams.coin(F.col("item_id").cast("string")) < 0.2, ~F.col("correct")).otherwise(F.col("correct")))
    losses = learned.two_stage([("synthetic", noisy), ("gold", rows.withColumn("y", F.col("correct")))], FEATURES, "y", steps=8)
    return spark.createDataFrame(losses, "stage string, step int, loss double")
