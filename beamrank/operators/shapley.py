"""Shapley values and ablations over score tables (backbone, rr_origin, metric, mask, value).

A mask has a bit for each component. Score tables have at most two to the number of players rows for
each system, so that the joins below are broadcasts of a bounded side.
"""

from __future__ import annotations

from math import factorial

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

KEYS = ["backbone", "rr_origin", "metric"]
PLAYERS = {"ir": 1, "gs": 2, "pp": 4, "rr": 8}


def lattice(spark: SparkSession, players: dict[str, int]) -> DataFrame:
    """Every subset of the players: mask, its size and its names in order."""
    names = F.array(*[F.when(F.expr(f"(mask & {bit}) > 0"), F.lit(name)) for name, bit in players.items()])
    rows = spark.range(1 << len(players)).select(F.col("id").cast("int").alias("mask"))
    return rows.select("mask", F.bit_count("mask").alias("size"), F.concat_ws("+", F.array_compact(names)).alias("components"))


def _players(spark: SparkSession, players: dict[str, int]) -> DataFrame:
    return spark.createDataFrame(list(players.items()), "player string, bit int")


def marginals(scores: DataFrame, players: dict[str, int] | None = None) -> DataFrame:
    """A row for each player and set of others where both scores are known."""
    who = F.broadcast(_players(scores.sparkSession, players or PLAYERS))
    without = scores.select(*KEYS, F.col("mask").alias("context"), F.col("value").alias("v0"))
    added = scores.select(*KEYS, F.col("mask").alias("m1"), F.col("value").alias("v1"))
    rows = without.join(who, F.expr("(context & bit) = 0")).withColumn("m1", F.expr("context + bit"))
    return rows.join(F.broadcast(added), [*KEYS, "m1"]).select(*KEYS, "player", "context", (F.col("v1") - F.col("v0")).alias("delta"))


def weight(size: Column, m: int) -> Column:
    """Share of the orders of m players in which just these ``size`` come before the one."""
    value = F.lit(0.0)
    for s in range(m):
        value = F.when(size == s, factorial(s) * factorial(m - s - 1) / factorial(m)).otherwise(value)
    return value


def _weighed(scores: DataFrame, players: dict[str, int]) -> DataFrame:
    bits = sum(players.values())
    return marginals(scores, players).withColumn("w", weight(F.expr(f"bit_count(context & {bits})"), len(players)))


def exact(scores: DataFrame, players: dict[str, int] | None = None) -> DataFrame:
    """Shapley values; refuses systems whose lattice is not complete."""
    players = players or PLAYERS
    whole = 1 << len(players)
    value = F.when(F.count(F.lit(1)) == whole // 2, F.round(F.sum(F.col("w") * F.col("delta")), 6)).otherwise(F.raise_error("incomplete lattice"))
    return _weighed(scores, players).groupBy(*KEYS, "player").agg(value.alias("phi"))


def available_mean(scores: DataFrame, players: dict[str, int] | None = None) -> DataFrame:
    """The plain mean of the marginals that are known, and how many they are."""
    return marginals(scores, players).groupBy(*KEYS, "player").agg(F.round(F.avg("delta"), 6).alias("phi"), F.count(F.lit(1)).alias("contexts"))


def available_weighted(scores: DataFrame, players: dict[str, int] | None = None) -> DataFrame:
    """Known marginals with Shapley's weights scaled to one."""
    rows = _weighed(scores, players or PLAYERS)
    return rows.groupBy(*KEYS, "player").agg(F.round(F.sum(F.col("w") * F.col("delta")) / F.sum("w"), 6).alias("phi"))


def sampled(scores: DataFrame, players: dict[str, int], orders: int, seed: int = 42) -> DataFrame:
    """Mean marginal along orders drawn by hash."""
    spark = scores.sparkSession
    who = F.broadcast(_players(spark, players))
    draw = F.md5(F.concat_ws(":", "order", "player", F.lit(seed)))
    before = Window.partitionBy("order").orderBy(draw, "player").rowsBetween(Window.unboundedPreceding, -1)
    prefix = spark.range(orders).toDF("order").crossJoin(who).withColumn("m0", F.coalesce(F.sum("bit").over(before), F.lit(0)).cast("int"))
    low, high = scores.select(*KEYS, F.col("mask").alias("m0"), F.col("value").alias("v0")), scores.select(*KEYS, F.col("mask").alias("m1"), F.col("value").alias("v1"))
    rows = prefix.withColumn("m1", F.expr("m0 + bit")).join(F.broadcast(low), "m0").join(F.broadcast(high), [*KEYS, "m1"])
    return rows.groupBy(*KEYS, "player").agg(F.round(F.avg(F.col("v1") - F.col("v0")), 6).alias("phi"))


def overall(values: DataFrame) -> DataFrame:
    """The mean over the origins of the reranker."""
    return values.groupBy("backbone", "metric", "player").agg(F.round(F.avg("phi"), 6).alias("phi"))


def two_rerankers(scores: DataFrame) -> DataFrame:
    """The two rerankers as players of their own; coalitions of both are not known."""
    five = {"ir": 1, "gs": 2, "pp": 4, "rr_alg": 8, "rr_seq": 16}
    second = (F.col("rr_origin") == "seq") & F.expr("(mask & 8) > 0")
    rows = scores.withColumn("mask", F.when(second, F.col("mask") + 8).otherwise(F.col("mask"))).withColumn("rr_origin", F.lit("both")).distinct()
    return available_mean(rows, five)


def efficiency(scores: DataFrame, players: dict[str, int]) -> DataFrame:
    """Sum of the values less what all players together add; zero for exact values."""
    bits = sum(players.values())
    ends = scores.groupBy(*KEYS).agg(
        (F.max(F.when(F.expr(f"(mask & {bits}) = {bits}"), F.col("value"))) - F.max(F.when(F.expr(f"(mask & {bits}) = 0"), F.col("value")))).alias("gain")
    )
    sums = exact(scores, players).groupBy(*KEYS).agg(F.sum("phi").alias("phi"))
    return sums.join(F.broadcast(ends), KEYS).select(*KEYS, F.round(F.abs(F.col("phi") - F.col("gain")), 4).alias("gap"))


def extremes(values: DataFrame) -> DataFrame:
    by = F.struct("phi", "player")
    return values.groupBy("backbone", "metric").agg(F.max_by("player", by).alias("strongest"), F.min_by("player", by).alias("weakest"))


def delta(scores: DataFrame, player: str = "ir") -> DataFrame:
    """What one component alone adds to the bare system, in points."""
    bit = PLAYERS[player]
    return marginals(scores, {player: bit}).where("context = 0").select(*KEYS, "player", F.round("delta", 6).alias("points"))


def interactions(scores: DataFrame, a: str = "gs", b: str = "pp") -> DataFrame:
    """v(with both) - v(with a) - v(with b) + v(with neither), for each set of others."""
    x, y = PLAYERS[a], PLAYERS[b]
    v = lambda m, name: F.broadcast(scores.select(*KEYS, (F.col("mask") - m).alias("context"), F.col("value").alias(name)))
    base = scores.where(F.expr(f"(mask & {x + y}) = 0")).select(*KEYS, F.col("mask").alias("context"), F.col("value").alias("v0"))
    rows = base.join(v(x, "va"), [*KEYS, "context"]).join(v(y, "vb"), [*KEYS, "context"]).join(v(x + y, "vab"), [*KEYS, "context"])
    return rows.select(*KEYS, "context", F.round(F.expr("vab - va - vb + v0"), 6).alias("interaction"))


def leave_one_out(scores: DataFrame, full: int = 15) -> DataFrame:
    return marginals(scores).where(F.expr(f"context + case player when 'ir' then 1 when 'gs' then 2 when 'pp' then 4 else 8 end = {full}")).select(*KEYS, "player", F.round("delta", 6).alias("loss"))


def all_vs_best(scores: DataFrame, full: int = 15) -> DataFrame:
    """The best set of components, and its lead over all of them together."""
    best = F.max(F.struct("value", (-F.col("mask")).alias("m")))
    whole = F.max(F.when(F.col("mask") == full, F.col("value")))
    rows = scores.groupBy(*KEYS).agg(best.alias("b"), whole.alias("whole"))
    return rows.where("whole is not null").select(*KEYS, (-F.col("b.m")).alias("best_mask"), F.round(F.col("b.value") - F.col("whole"), 6).alias("lead"))


def staged(scores: DataFrame) -> DataFrame:
    """Keep, for each backbone, the better of plain and IR; then the best set that agrees with it. Of equals the least."""
    first = scores.where("mask in (0, 1)").groupBy(*KEYS).agg(F.max_by("mask", F.struct("value", (-F.col("mask")).alias("m"))).alias("base"))
    rows = scores.join(F.broadcast(first), KEYS).where("(mask & 1) = base")
    pick = F.struct("value", (-F.col("mask")).alias("m"))
    return rows.groupBy(*KEYS, "base").agg((-F.max(pick)["m"]).alias("best_mask"), F.count(F.lit(1)).alias("runs"))


def best_system(scores: DataFrame) -> DataFrame:
    """The best system of all by each metric."""
    pick = F.max(F.struct("value", (-F.col("mask")).alias("m"), "backbone", "rr_origin"))
    return scores.groupBy("metric").agg(pick.alias("b")).select("metric", F.col("b.backbone").alias("backbone"), F.col("b.rr_origin").alias("rr_origin"), (-F.col("b.m")).alias("mask"), F.col("b.value").alias("value"))
