"""Rerankers: a beam in, one candidate out.

Choices by verdict and rank are minima of packed numbers, so that the aggregate is a hash aggregate
with map-side combination; choices by score order by score and rank within each beam. Texts are joined
back by identifier afterwards.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from beamrank.sources.io import stored

_BIG = 1 << 32


def _first(key: Column) -> Column:
    return F.min_by("item_id", key)


def _chosen(df: DataFrame, key: Column) -> DataFrame:
    """beam_id, item_id and whether it is correct, of the least key of each beam."""
    return df.groupBy("beam_id").agg(F.min_by("item_id", key).alias("item_id"), F.min_by("correct", key).alias("correct"))


def top1(df: DataFrame) -> DataFrame:
    return _chosen(df, F.col("pos").cast("bigint"))


def verifier(df: DataFrame, verdict: Column | None = None) -> DataFrame:
    """The first accepted item; if none is, the first of the beam. A null verdict does not accept."""
    verdict = F.col("verified") if verdict is None else verdict
    return _chosen(df, F.when(F.coalesce(verdict, F.lit(False)), 0).otherwise(_BIG) + F.col("pos"))


def by_score(df: DataFrame, k: int = 5, score: str = "score") -> DataFrame:
    """The best score among the first ``k``; of equal ones the first."""
    best = F.struct(-F.coalesce(F.col(score), F.lit(float("-inf"))), F.col("pos"))
    rank = F.row_number().over(Window.partitionBy("beam_id").orderBy(best))
    return df.where(F.col("pos") <= k).withColumn("r", rank).where("r = 1").select("beam_id", "item_id", "correct")


def selector(df: DataFrame, k: int = 5, score: str = "score") -> DataFrame:
    """The choice of a selector whose scores are given, among the first ``k`` items."""
    return by_score(df, k, score)


def binary_beams(df: DataFrame, second: str = "rank") -> DataFrame:
    """The first item and the best accepted one of the rest (by rank, or by score), side by side."""
    rest = (F.col("pos") > 1) & F.coalesce("verified", F.lit(False))
    if second == "rank":
        key = F.when(rest, F.col("pos").cast("bigint"))
        pick = lambda c: F.min_by(c, key)
    else:
        key = F.when(rest, F.struct(F.col("score"), (-F.col("pos")).alias("p")))
        pick = lambda c: F.max_by(c, key)
    one = F.when(F.col("pos") == 1, F.col("pos").cast("bigint"))
    first = lambda c: F.min_by(c, one)
    return df.groupBy("beam_id").agg(
        *[first(c).alias(f"{c}_1") for c in ("item_id", "correct", "score")], *[pick(c).alias(f"{c}_2") for c in ("item_id", "correct", "score")]
    )


def hybrid(df: DataFrame, second: str = "rank") -> DataFrame:
    """The binary selector's choice of the pair: the second if its score is strictly larger.

    Without an accepted item after the first, the first stays and the selector is not asked.
    """
    takes = F.coalesce(F.col("score_2") > F.col("score_1"), F.lit(False))
    pair = binary_beams(df, second)
    return pair.select("beam_id", *[F.when(takes, F.col(f"{c}_2")).otherwise(F.col(f"{c}_1")).alias(c) for c in ("item_id", "correct")])


def ceiling(df: DataFrame) -> DataFrame:
    """What a perfect reranker would choose: the first correct item, else the first."""
    return _chosen(df, F.when(F.col("correct"), 0).otherwise(_BIG) + F.col("pos"))


def random_key(seed: int = 42) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws(":", "beam_id", "pos", F.lit(seed))), 1, 12), 16, 10).cast("bigint") * 1024 + F.col("pos")


def random(df: DataFrame, seed: int = 42) -> DataFrame:
    return _chosen(df, random_key(seed))


def linking(df: DataFrame, score: str = "score") -> DataFrame:
    """The item with the most question words linked to it; an approximation of linking heuristics."""
    return by_score(df, 1 << 30, score)


def waves(df: DataFrame, verdicts, sizes: tuple[int, ...] = (1, 5)) -> DataFrame:
    """The verifier's choice when verdicts are dear: ``verdicts(items)`` adds ``verified`` to items.

    Ranks are judged in waves; beams with an accepted item take no part in later ones. What a wave
    accepts is stored, so that no item is judged twice.
    """
    low, left, settled = 0, df, None
    for high in (*sizes, None):
        wave = left.where(F.col("pos") > low) if high is None else left.where((F.col("pos") > low) & (F.col("pos") <= high))
        hits = stored(verdicts(wave).where("verified").groupBy("beam_id").agg(F.min("pos").alias("pos")), "wave")
        settled = hits if settled is None else settled.union(hits)
        left, low = left.join(hits.select("beam_id"), "beam_id", "left_anti"), high or 0
    chosen = df.join(settled, ["beam_id", "pos"]).select("beam_id", "item_id", "correct")
    return chosen.union(left.where("pos = 1").select("beam_id", "item_id", "correct"))


def flips(before: DataFrame, after: DataFrame) -> DataFrame:
    """Beams by whether they were right before and are right after."""
    b, a = before.select("beam_id", F.col("correct").alias("was")), after.select("beam_id", F.col("correct").alias("now"))
    return b.join(a, "beam_id").groupBy("was", "now").agg(F.count(F.lit(1)).alias("beams"))


RERANKERS = {"top1": top1, "verifier": verifier, "selector": selector, "hybrid": hybrid, "ceiling": ceiling, "random": random}
