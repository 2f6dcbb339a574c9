"""Exact deduplication with a heavy-hitter split.

1. Each row is reduced to its identifier and the SHA-256 of its text, written once.
2. A Misra-Gries summary (Spark's frequent-item aggregate) names at most ``counters`` digests that
   may be frequent. Their exact counts are then taken, and those above rows / counters win. There
   are at most ``counters`` winners whatever the input, so they are broadcast, and rows of a
   winning digest get their answer on the map side: they are never shuffled.
3. All other digests have at most rows / counters rows each and take an ordinary shuffle.

Edge cases. A null text counts as empty. Repeated rows (same identifier and text) are copies of one
another: one of them stays. A null identifier is smaller than any other; a group of only null
identifiers keeps one row, and its ``keep_id`` is null. An empty table gives an empty result. Extra
columns, whatever their names, are not read by ``exact_groups`` and pass through ``exact_dedup``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm.common import BROADCAST_ROWS, bounded_broadcast, durable, text_or_empty

COUNTERS = 1000


def digest_of(text: str = "text") -> Column:
    return F.sha2(text_or_empty(text), 256)


def heavy_hitters(rows: DataFrame, key: str, n_rows: int, counters: int = COUNTERS) -> DataFrame:
    """Values of ``key`` with more than n_rows / counters rows, with exact figures of each.

    The summary holds 64-bit hashes of the key, and the exact count is by the key itself.
    """
    hashed = rows.select(F.xxhash64(key).alias("h"))
    maybe = hashed.stat.freqItems(["h"], 1.0 / counters).select(F.explode("h_freqItems").alias("h"))
    found = rows.withColumn("h", F.xxhash64(key)).join(F.broadcast(maybe), "h", "left_semi")
    return (
        found.groupBy(key)
        .agg(F.count(F.lit(1)).alias("group_size"), F.max("doc_id").alias("keep_id"), F.coalesce(F.max_by("row_no", "doc_id"), F.max("row_no")).alias("keep_row"))
        .where(F.col("group_size") > n_rows / counters)
    )


def exact_groups(docs: DataFrame, text: str = "text", counters: int = COUNTERS) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256."""
    rows = durable(docs.select("doc_id", digest_of(text).alias("text_sha256"), F.monotonically_increasing_id().alias("row_no")), "digests")
    n = rows.count()
    heavy = durable(heavy_hitters(rows, "text_sha256", n, counters), "heavy")
    hot = rows.join(F.broadcast(heavy), "text_sha256").withColumn("kept", F.col("row_no") == F.col("keep_row"))
    group = Window.partitionBy("text_sha256")
    rank = group.orderBy(F.col("doc_id").desc_nulls_last(), F.col("row_no").desc())
    cold = (
        rows.join(F.broadcast(heavy.select("text_sha256")), "text_sha256", "left_anti")
        .withColumn("kept", F.row_number().over(rank) == 1)
        .withColumn("group_size", F.count(F.lit(1)).over(group))
        .withColumn("keep_id", F.max("doc_id").over(group))
    )
    names = ["doc_id", "keep_id", "group_size", "kept", "text_sha256"]
    return hot.select(*names).unionByName(cold.select(*names))


def exact_dedup(docs: DataFrame, text: str = "text", counters: int = COUNTERS, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Rows of ``docs`` that stay, with all their columns.

    Only identifiers and digests of what goes are joined back. If they are few they are broadcast
    and texts are not moved; otherwise the join shuffles.
    """
    groups = durable(exact_groups(docs, text, counters), "groups")
    pairs = groups.groupBy("doc_id", "text_sha256").agg(F.max("kept").alias("kept"), F.count(F.lit(1)).alias("n")).where("not kept or n > 1")
    pairs = durable(pairs.toDF("id", "digest", "kept", "n"), "goes")
    pairs = bounded_broadcast(pairs, pairs.count(), broadcast_rows)
    # rows travel whole under one name, so that no column of theirs can clash
    keyed = docs.select(digest_of(text).alias("own"), F.col("doc_id").alias("own_id"), F.struct("*").alias("row"))
    on = (F.col("own") == F.col("digest")) & F.col("own_id").eqNullSafe(F.col("id"))
    once = keyed.join(pairs, on, "left_anti").select("row.*")
    again = keyed.join(pairs.where("kept"), on).select("own", "own_id", "row")
    one = Window.partitionBy("own", "own_id").orderBy(F.lit(0))
    again = again.withColumn("rank", F.row_number().over(one)).where("rank = 1").select("row.*")
    return once.union(again)
