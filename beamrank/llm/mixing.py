"""Mixing sources to target weights by whole and fractional repetition.

Words are summed for each source; targets share all words by weight, none above ``max_repeat``
times its source. A document is emitted floor(rate) times, and once more if a number drawn by hash
from its identifier is below the fraction. Of a fixed list of seeds a source takes the one whose
draw comes nearest to its target, so that small sources with a few long documents come near it too;
at scale all seeds are as good. Nothing depends on partitions or order: reruns agree.

Sources are few by nature. Their table is broadcast only up to a counted bound, and is joined with
a shuffle beyond it.

Edge cases. A null text has no words. Null sources form one source, the last. A source without
words has target 0 and rate 0, so its documents are not emitted. Repeated rows are drawn alike. Null
identifiers draw as the empty string. An empty table gives an empty result. Extra columns pass
through ``mix`` and are not read by ``mix_counts``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm.common import bounded_broadcast, durable

WEIGHTS = (5, 2, 1)
MAX_REPEAT = 3
SEEDS = 16
SOURCE_ROWS = 100_000
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("bigint")


def draw(doc_id: Column, seed: int) -> Column:
    """A number in [0, 1) from the identifier; four seeds share an MD5."""
    digest = F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(f":{seed // 4}")))
    return F.conv(F.substring(digest, 8 * (seed % 4) + 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def source_targets(sizes: DataFrame, weights=WEIGHTS, max_repeat: int = MAX_REPEAT) -> DataFrame:
    """source, source_size, target, rate: by weight, filled up to the limit of each source.

    Sources that reach their limit are the first in order of size over weight; the others share
    what is left by weight. The level that fits is found from running sums, without iteration.
    """
    by_source = sizes.groupBy("source").agg(F.sum("size").cast("bigint").alias("source_size"))
    one = Window.partitionBy(F.lit(0))
    name_order = one.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.row_number().over(name_order) - 1) % len(weights) + 1).cast("int"))
    ranked = by_source.withColumn("weight", weight)
    fill = one.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    upto = fill.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    onward = fill.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    levels = ranked.withColumn(
        # the level at which this source and all after it share what the sources before leave
        "level", (F.sum("source_size").over(one) - max_repeat * (F.sum("source_size").over(upto) - F.col("source_size"))) / F.sum("weight").over(onward)
    )
    fits = F.col("level") * F.col("weight") <= max_repeat * F.col("source_size")
    # the first that fits; levels after it only fall
    level = F.max(F.when(fits, F.col("level"))).over(one)
    target = F.least(F.lit(float(max_repeat)) * F.col("source_size"), level * F.col("weight"))
    out = levels.withColumn("target", F.coalesce(target, F.lit(0.0)))
    rate = F.when(F.col("source_size") > 0, F.least(F.lit(float(max_repeat)), F.col("target") / F.col("source_size"))).otherwise(F.lit(0.0))
    return out.select("source", "source_size", "target", rate.alias("rate"))


def mix_counts(docs: DataFrame, weights=WEIGHTS, max_repeat: int = MAX_REPEAT, seeds: int = SEEDS) -> DataFrame:
    """doc_id, source, size, source_size, target, rate and copies of every row of ``docs``."""
    sizes = durable(docs.select("doc_id", "source", word_count().alias("size")), "words")
    targets = durable(source_targets(sizes, weights, max_repeat), "targets")
    targets = bounded_broadcast(targets, targets.count(), SOURCE_ROWS)
    rated = sizes.withColumnRenamed("source", "s").join(targets, F.col("s").eqNullSafe(F.col("source"))).drop("s")
    fraction = F.col("rate") - F.floor("rate")
    extra = [F.sum(F.when(draw(F.col("doc_id"), k) < fraction, F.col("size")).otherwise(0)).alias(f"x{k}") for k in range(seeds)]
    sums = rated.groupBy("source").agg(F.first("rate").alias("rate"), F.first("source_size").alias("source_size"), F.first("target").alias("target"), *extra)
    misses = F.array(*[F.struct(F.abs(F.floor("rate") * F.col("source_size") + F.col(f"x{k}") - F.col("target")).alias("miss"), F.lit(k).alias("k")) for k in range(seeds)])
    chosen = durable(sums.select("source", "source_size", "target", "rate", F.array_min(misses)["k"].alias("seed")), "seeds")
    chosen = bounded_broadcast(chosen, chosen.count(), SOURCE_ROWS)
    out = sizes.withColumnRenamed("source", "s").join(chosen, F.col("s").eqNullSafe(F.col("source"))).drop("s")
    number = F.element_at(F.array(*[draw(F.col("doc_id"), k) for k in range(seeds)]), F.col("seed") + 1)
    copies = (F.floor("rate") + F.when(number < fraction, 1).otherwise(0)).cast("bigint")
    return out.withColumn("copies", copies)


def mix(docs: DataFrame, weights=WEIGHTS, max_repeat: int = MAX_REPEAT, seeds: int = SEEDS) -> DataFrame:
    """The mixture itself: every row as many times as its copies, with the columns of ``docs``."""
    rates = mix_counts(docs, weights, max_repeat, seeds).select("source", "rate", "seed").distinct()
    rates = durable(rates, "rates")
    rates = bounded_broadcast(rates, rates.count(), SOURCE_ROWS)
    number = F.element_at(F.array(*[draw(F.col("own_id"), k) for k in range(seeds)]), F.col("seed") + 1)
    copies = (F.floor("rate") + F.when(number < F.col("rate") - F.floor("rate"), 1).otherwise(0)).cast("int")
    # rows travel whole under one name, so that no column of theirs can clash
    keyed = docs.select(F.col("source").alias("own_source"), F.col("doc_id").alias("own_id"), F.struct("*").alias("row"))
    rated = keyed.join(rates, F.col("own_source").eqNullSafe(F.col("source"))).withColumn("copies", copies).where("copies > 0")
    return rated.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")
