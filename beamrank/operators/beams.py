"""Building, reordering and analysing ranked beams.

All take long beam tables and cost one exchange by beam at most; what needs only the first items of
a beam filters on the rank, which Spark turns into a limit for each group before the exchange.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

KEEP = 0.7
SEED = 42


def first_k(df: DataFrame, k: int) -> DataFrame:
    return df.where(F.col("pos") <= k)


def with_gold(df: DataFrame, by: str = "price") -> DataFrame:
    """Mark the gold item of each beam: the one with the largest ``by``, of equal ones the first."""
    best = F.max(F.struct(F.col(by), (-F.col("pos")).alias("p"))).over(Window.partitionBy("beam_id"))
    return df.withColumn("gold_pos", -best["p"])


def ensure_gold(df: DataFrame, k: int = 5, mode: str = "replace_last") -> DataFrame:
    """The first ``k`` items of each beam with its gold item put in if it is not among them.

    ``replace_last`` puts it in the k-th place; ``front`` puts it first and moves the others on.
    """
    absent, gold = F.col("gold_pos") > k, F.col("pos") == F.col("gold_pos")
    if mode == "replace_last":
        place = F.when(absent & gold, k).otherwise(F.col("pos"))
        stays = ~(absent & ~gold & (F.col("pos") == k))
    elif mode == "front":
        place = F.when(absent & gold, 1).when(absent, F.col("pos") + 1).otherwise(F.col("pos"))
        stays = F.lit(True)
    else:
        raise ValueError(mode)
    moved = df.withColumn("new_pos", place.cast("int")).where(stays & ((F.col("pos") <= k) | gold)).where(F.col("new_pos") <= k)
    return moved.withColumn("is_gold", gold).drop("pos", "gold_pos").withColumnRenamed("new_pos", "pos")


def insert_gold(df: DataFrame, gold: DataFrame, k: int = 5, mode: str = "replace_last", on: str = "item_id") -> DataFrame:
    """The first ``k`` items of each beam, and the beam's gold item if none of them matches it.

    ``gold`` has one row for each beam, with the columns of ``df`` but ``pos``, from wherever it came: it need not
    be in the beam. An item matches if it equals the gold item in column ``on``: the text, a key of its
    components, or the fingerprint of its result. ``replace_last`` puts the gold item in place k, or
    after a shorter beam; ``front`` puts it first and moves the others on. Beams without a gold row stay.
    """
    names = [c for c in df.columns if c != "pos"]
    items = first_k(df, k).select(*names, "pos", F.lit(False).alias("own"))
    both = items.unionByName(gold.select(*names, F.lit(0).cast("int").alias("pos"), F.lit(True).alias("own")))
    beam = Window.partitionBy("beam_id")
    key = F.max(F.when(F.col("own"), F.col(on))).over(beam)
    same = F.coalesce(F.col(on) == key, F.lit(False))
    marked = both.withColumn("is_gold", same).withColumn("n", F.count_if(~F.col("own")).over(beam))
    marked = marked.withColumn("absent", F.max(F.col("own")).over(beam) & ~F.coalesce(F.max(F.col("is_gold") & ~F.col("own")).over(beam), F.lit(False)))
    own, absent = F.col("own"), F.col("absent")
    if mode == "replace_last":
        place = F.when(own, F.least(F.col("n") + 1, F.lit(k))).otherwise(F.col("pos"))
        stays = own | ~absent | (F.col("pos") < k)
    elif mode == "front":
        place, stays = F.when(own, 1).when(absent, F.col("pos") + 1).otherwise(F.col("pos")), F.lit(True)
    else:
        raise ValueError(mode)
    kept = marked.where(absent | ~own).withColumn("place", place.cast("int")).where(stays & (F.col("place") <= k))
    return kept.select(*names, F.col("place").alias("pos"), "is_gold")


def with_gold_first(df: DataFrame, k: int) -> DataFrame:
    """The first ``k`` items of each beam, its gold item in first place if not among them, and labelled correct."""
    return ensure_gold(with_gold(df), k, "front").withColumn("correct", F.col("correct") | F.col("is_gold"))


def coin(*parts: Column) -> Column:
    """A number in [0, 1) by hash of its parts; the same in any engine with MD5."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") / float(1 << 32)


def reorder_random(df: DataFrame, seed: int = SEED) -> DataFrame:
    """Items of each beam in an order drawn by hash."""
    draw = F.md5(F.concat_ws(":", "beam_id", "pos", F.lit(seed)))
    return df.withColumn("new_pos", F.row_number().over(Window.partitionBy("beam_id").orderBy(draw, "pos")))


def geometric_shift(beam: Column, size: Column, k: int, keep: float = KEEP) -> Column:
    """How many places the first item moves on: tails in a row of a coin that keeps with ``keep``."""
    shift = F.least(size, F.lit(k)) - 1
    for i in range(k - 1, 0, -1):
        shift = F.when(F.least(size, F.lit(k)) <= i, F.least(size, F.lit(k)) - 1).when(coin(beam, F.lit(i)) < keep, i - 1).otherwise(shift)
    return shift


def reorder_geometric(df: DataFrame, k: int = 5, keep: float = KEEP, anchor: str = "first") -> DataFrame:
    """Move a correct item as far as the coins of its beam say, within the first k; those it passes move up by one.

    In closed form: no array is rewritten. With ``anchor`` "first" it is the first item, and beams in which that
    is not correct stay as they are; with "first_correct" it is the first correct one, wherever it stands.
    """
    whole = Window.partitionBy("beam_id")
    size = F.least(F.count(F.lit(1)).over(whole), F.lit(k))
    start = F.min(F.when(F.col("correct"), F.col("pos"))).over(whole)
    walks = start == 1 if anchor == "first" else start <= size
    if anchor not in ("first", "first_correct"):
        raise ValueError(anchor)
    moved = df.withColumn("start", F.when(walks, start)).withColumn("room", size - F.col("start") + 1)
    moved = moved.withColumn("goal", F.col("start") + geometric_shift(F.col("beam_id").cast("string"), F.col("room"), k, keep))
    passed = (F.col("pos") > F.col("start")) & (F.col("pos") <= F.col("goal"))
    place = F.when(F.col("pos") == F.col("start"), F.col("goal")).when(passed, F.col("pos") - 1).otherwise(F.col("pos"))
    return moved.withColumn("new_pos", place.cast("int")).drop("start", "room", "goal")


def first_correct(df: DataFrame) -> DataFrame:
    """beam_id and the rank of its first correct item, null if it has none."""
    return df.groupBy("beam_id").agg(F.min(F.when(F.col("correct"), F.col("pos"))).alias("first_pos"))


def position_hist(df: DataFrame) -> DataFrame:
    return first_correct(df).groupBy("first_pos").agg(F.count(F.lit(1)).alias("beams"))


def gain_curve(df: DataFrame, *by: str) -> DataFrame:
    """For each k: how many beams have a correct item among their first k, and their share.

    After one aggregate by beam the rest is as many rows as beams are wide.
    """
    firsts = df.groupBy("beam_id", *by).agg(F.min(F.when(F.col("correct"), F.col("pos"))).alias("first_pos"), F.max("pos").alias("width"))
    totals = firsts.groupBy(*by).agg(F.count(F.lit(1)).alias("beams"), F.max("width").alias("widest"))
    hits = firsts.where("first_pos is not null").groupBy(*by, F.col("first_pos").alias("k")).agg(F.count(F.lit(1)).alias("hits"))
    grid = totals.withColumn("k", F.explode(F.sequence(F.lit(1), F.col("widest"))))
    run = Window.partitionBy(*by).orderBy("k") if by else Window.orderBy("k")
    out = grid.join(hits, [*by, "k"], "left").withColumn("covered", F.sum(F.coalesce("hits", F.lit(0))).over(run))
    return out.select(*by, "k", "covered", F.round(F.col("covered") / F.col("beams"), 6).alias("share"))


def headroom(df: DataFrame) -> DataFrame:
    """Share of beams right at the top, share right anywhere, and what reranking could gain."""
    one = df.groupBy("beam_id").agg(F.max(F.col("correct") & (F.col("pos") == 1)).alias("top"), F.max("correct").alias("any"))
    top, ceiling = F.avg(F.col("top").cast("int")), F.avg(F.col("any").cast("int"))
    return one.agg(F.round(top, 6).alias("top1"), F.round(ceiling, 6).alias("ceiling"), F.round(ceiling - top, 6).alias("headroom"))


def best_by_potential(curves: DataFrame, k: int) -> DataFrame:
    """The system whose beams have the largest share covered within ``k``."""
    return curves.where(F.col("k") == k).agg(F.max_by("system", F.struct("share", "system")).alias("system"), F.max("share").alias("share"))


def label_distribution(df: DataFrame, *by: str) -> DataFrame:
    right = F.count_if("correct")
    return df.groupBy(*by).agg(right.alias("positive"), F.count_if(~F.col("correct")).alias("negative"), F.round(100 * right / F.count(F.lit(1)), 4).alias("percent"))


def dictionary(texts: DataFrame, text: str) -> DataFrame:
    """Distinct texts with a 64-bit identifier each, and whether another text shares it."""
    distinct = texts.select(text).distinct().withColumn("sql_id", F.xxhash64(text))
    clash = F.count(F.lit(1)).over(Window.partitionBy("sql_id")) > 1
    return distinct.withColumn("clash", clash)
