"""Accuracy measures, each one aggregate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def accuracy(df: DataFrame, hit: str = "correct") -> DataFrame:
    right = F.count_if(F.coalesce(hit, F.lit(False)))
    return df.agg(right.alias("right"), F.count(F.lit(1)).alias("total"), F.round(right / F.count(F.lit(1)), 6).alias("accuracy"))


def prf(df: DataFrame, *by: str, accepted: str = "verified", truth: str = "correct") -> DataFrame:
    """Confusion counts, precision, recall and F1; a measure without denominator is null."""
    a, t = F.coalesce(accepted, F.lit(False)), F.col(truth)
    tp, fp, fn, tn = F.count_if(a & t), F.count_if(a & ~t), F.count_if(~a & t), F.count_if(~a & ~t)
    out = df.groupBy(*by).agg(tp.alias("tp"), fp.alias("fp"), fn.alias("fn"), tn.alias("tn"))
    ratio = lambda x, y: F.round(F.try_divide(x.cast("double"), y.cast("double")), 6)
    return out.select(
        *by, "tp", "fp", "fn", "tn",
        ratio(F.col("tp"), F.col("tp") + F.col("fp")).alias("precision"),
        ratio(F.col("tp"), F.col("tp") + F.col("fn")).alias("recall"),
        ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")).alias("f1"),
    )


def mean_reciprocal_rank(df: DataFrame) -> DataFrame:
    firsts = df.groupBy("beam_id").agg(F.min(F.when(F.col("correct"), F.col("pos"))).alias("p"))
    return firsts.agg(F.round(F.avg(F.coalesce(1 / F.col("p"), F.lit(0.0))), 6).alias("mrr"))
