"""Sharding by histogram sort: equal bytes in each shard, found by counting alone.

Rows are reduced to (key, size) once. Then, in rounds, exact bytes and rows are counted in the
sub-ranges of every key range that still holds an unsettled boundary, and the range is narrowed to
the sub-range in which the target falls. A splitter is settled when a boundary between two keys is
within ``tolerance`` of its target, or when its range holds no further boundary. The driver sees
only counts of ``probes`` sub-ranges for each open splitter. At the end rows move once.

Keys are 60-bit: 40 bits of a hash of the group (here: the text), then 20 of a hash of the
identifier. Equal texts are neighbours. Splitters lie between groups; only a group of more bytes than a
shard's share is cut, as the law of equal bytes could not hold otherwise.

Edge cases. A null text has no bytes, and each row has 16 bytes besides. Rows of one key stay
together; identical rows are interchangeable. With fewer rows than shards some shards are empty. An
empty table gives an empty result. Null identifiers are hashed as the empty string. Other columns
are not read.
"""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm.common import bounded_broadcast, durable, text_or_empty

KEY_BITS = 60
#: The low bits of a key, which tell rows of a group apart.
LOW_BITS = 20
OVERHEAD = 16
SHARDS = 40
PROBES = 1024
#: Sub-ranges of each shard that are put in order on their own.
PIECES = 64
#: Rows that one task should put in order; a sub-range with more is cut at quantiles of its keys, as many texts may be equal.
PIECE_ROWS = 1_000_000
CUTS = 1000


def hash_bits(value: Column, digits: int) -> Column:
    """The first hexadecimal digits of the MD5 of a string, as a number."""
    return F.conv(F.substring(F.md5(value), 1, digits), 16, 10).cast("bigint")


def spread_key(text: Column, doc_id: Column) -> Column:
    low = hash_bits(F.coalesce(doc_id.cast("string"), F.lit("")), 5)
    return hash_bits(text, 10) * F.lit(1 << 20) + low


def _step(key: Column, bounds: list[int], first: int = 0) -> Column:
    """How many of the ascending ``bounds`` are at or below the key, as a balanced tree of tests."""
    if not bounds:
        return F.lit(first)
    mid = len(bounds) // 2
    return F.when(key < F.lit(bounds[mid]), _step(key, bounds[:mid], first)).otherwise(_step(key, bounds[mid + 1 :], first + mid + 1))


def histogram_splitters(rows: DataFrame, shards: int, tolerance: float = 0.0, probes: int = PROBES) -> list[int]:
    """Ascending keys; a row belongs to the shard with as many of them at or below its key.

    ``rows`` has ``key`` in [0, 2^60) and ``size``. Every splitter is the boundary nearest to its
    share of the bytes, or the first found within ``tolerance`` of a shard's bytes.
    """
    total = rows.agg(F.coalesce(F.sum("size"), F.lit(0)).cast("bigint")).head()[0]
    end = 1 << KEY_BITS
    # distances are kept times the number of shards, so that they are whole numbers
    off = lambda j, below: abs(shards * below - total * j)
    best = {j: min((off(j, 0), 0), (off(j, total), end)) for j in range(1, shards)}
    open_at = dict.fromkeys(best, (0, end, 0)) if total else {}
    while open_at:
        ranges = sorted(set(open_at.values()))
        table = {}
        for cell in _counts(rows, ranges, probes):
            table.setdefault(cell["r"], []).append(cell)
        for r, (lo, hi, below) in enumerate(ranges):
            cells, at = sorted(table.get(r, []), key=lambda x: x["low"]), []
            for x in cells:
                at.append((x["low"], below))
                below += x["bytes"]
            at.append((hi, below))
            for j in [j for j, where in open_at.items() if where[:2] == (lo, hi)]:
                best[j] = min(best[j], *((off(j, under), key) for key, under in at))
                i = bisect_right([shards * under for _, under in at], total * j) - 1
                inner = cells[i] if 0 <= i < len(cells) else None
                if best[j][0] <= tolerance * total or inner is None or inner["low"] == inner["high"]:
                    del open_at[j]
                else:
                    open_at[j] = (inner["low"], inner["high"] + 1, at[i][1])
    return sorted(key for _, key in best.values())


def between_groups(rows: DataFrame, splitters: list[int], shards: int) -> list[int]:
    """Splitters moved to the nearer end of the group that they cut, unless it has more than a shard's share of the bytes.

    One scan counts the bytes below both ends of each such group, of which there are fewer than shards.
    """
    groups = {k >> LOW_BITS for k in splitters}
    ends = sorted({(g + side) << LOW_BITS for g in groups for side in (0, 1)})
    sums = {r["at"]: r["bytes"] for r in rows.groupBy(_step(F.col("key"), ends).alias("at")).agg(F.sum("size").cast("bigint").alias("bytes")).collect()}
    below, total = {}, 0
    for i, end in enumerate(ends):
        total += sums.get(i, 0)
        below[end] = total
    total += sums.get(len(ends), 0)
    out = []
    for j, key in enumerate(splitters, 1):
        low, high = (key >> LOW_BITS) << LOW_BITS, ((key >> LOW_BITS) + 1) << LOW_BITS
        if (below[high] - below[low]) * shards <= total:
            key = min((low, high), key=lambda x: (abs(shards * below[x] - total * j), x))  # noqa: B023
        out.append(key)
    return sorted(out)


def _counts(rows: DataFrame, ranges: list[tuple[int, int, int]], probes: int) -> list:
    """Exact bytes, and the least and largest key, in each of the ``probes`` equal parts of each range."""
    pick = lambda values: F.element_at(F.array(*[F.lit(v) for v in values]), F.col("r") + 1)
    starts, ends = [lo for lo, _, _ in ranges], [hi for _, hi, _ in ranges]
    return (
        rows.where((F.col("key") >= starts[0]) & (F.col("key") < ends[-1]))
        .withColumn("r", _step(F.col("key"), starts) - 1)
        .where(F.col("key") < pick(ends))
        .withColumn("lo", pick(starts))
        .withColumn("width", pick([max(1, -(-(hi - lo) // probes)) for lo, hi, _ in ranges]))
        .groupBy("r", F.expr("(key - lo) div width").alias("part"))
        .agg(F.sum("size").cast("bigint").alias("bytes"), F.min("key").alias("low"), F.max("key").alias("high"))
        .collect()
    )


def histogram_shards(rows: DataFrame, shards: int, tolerance: float = 0.0, probes: int = PROBES, pieces: int = PIECES, piece_rows: int = PIECE_ROWS) -> DataFrame:
    """``rows`` with ``shard`` and ``slot`` (place within the shard in key order, gapless from 0).

    Slots come from ranks within sub-ranges of a shard and the counts of the sub-ranges before, so
    that no task has to hold a whole shard. There are shards * pieces such counts, and up to CUTS for
    a sub-range of more than ``piece_rows`` rows, as of a short text that very many rows have.
    """
    splitters = between_groups(rows, histogram_splitters(rows, shards, tolerance, probes), shards)
    edges = [0, *splitters, 1 << KEY_BITS]
    pick = lambda values: F.element_at(F.array(*[F.lit(v) for v in values]), F.col("shard") + 1)
    lo, width = pick(edges[:-1]), pick([max(1, b - a) for a, b in zip(edges, edges[1:], strict=False)])
    placed = rows.withColumn("shard", _step(F.col("key"), splitters).cast("int")).withColumn(
        "piece", F.least(F.lit(pieces - 1), F.floor((F.col("key") - lo) / width * pieces)).cast("int")
    )
    large = durable(placed.groupBy("shard", "piece").count().where(F.col("count") > piece_rows).drop("count"), "large")
    if large.isEmpty():
        placed = placed.withColumn("part", F.lit(0))
    else:
        # no more rows than shards * pieces, each with CUTS keys
        shares = F.array(*[F.lit(i / CUTS) for i in range(1, CUTS)])
        cuts = placed.join(F.broadcast(large), ["shard", "piece"]).groupBy("shard", "piece").agg(F.percentile_approx("key", shares, F.lit(10 * CUTS)).alias("cuts"))
        known = placed.join(F.broadcast(durable(cuts, "cuts")), ["shard", "piece"], "left")
        placed = known.withColumn("part", F.coalesce(F.size(F.filter("cuts", lambda c: c <= F.col("key"))), F.lit(0))).drop("cuts")
        placed = placed.withColumn("part", F.greatest("part", F.lit(0)))
    before = Window.partitionBy("shard").orderBy("piece", "part").rowsBetween(Window.unboundedPreceding, -1)
    starts = durable(placed.groupBy("shard", "piece", "part").count().select("shard", "piece", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first")), "starts")
    inside = Window.partitionBy("shard", "piece", "part").orderBy("key", "doc_id")
    ranked = placed.withColumn("place", F.row_number().over(inside) - 1)
    starts = bounded_broadcast(starts, starts.count())
    return ranked.join(starts, ["shard", "piece", "part"]).withColumn("slot", (F.col("first") + F.col("place")).cast("bigint")).drop("piece", "part", "place", "first")


def shard_documents(docs: DataFrame, shards: int = SHARDS, tolerance: float = 0.0) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard (null under this law) per document."""
    text = text_or_empty()
    rows = durable(
        docs.select(
            "doc_id",
            (F.octet_length(text) + OVERHEAD).cast("bigint").alias("size"),
            F.crc32(F.encode(text, "utf-8")).alias("text_crc32"),
            spread_key(text, F.col("doc_id")).alias("key"),
        ),
        "sizes",
    )
    placed = histogram_shards(rows, shards, tolerance)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, shards: int = SHARDS) -> DataFrame:
    """Write whole documents into ``path``, a folder per shard, in slot order within each file. Returns the placement.

    Files have the columns of ``docs`` with ``slot``, in folders ``shard=n``; if ``docs`` has columns of these
    names, ours get underscores at the end until they differ. Rows with equal identifiers and texts share a shard, and the first of their slots.
    """
    taken = {c.lower() for c in docs.columns}
    shard_name, slot_name = (next(n + "_" * k for k in range(len(taken) + 1) if n + "_" * k not in taken) for n in ("shard", "slot"))
    placed = durable(shard_documents(docs, shards), "placed").select("doc_id", "text_crc32", "shard", "slot")
    once = placed.groupBy(F.col("doc_id").alias("id"), "text_crc32").agg(F.min(F.struct("shard", "slot")).alias("at"))
    keyed = docs.select(F.crc32(F.encode(text_or_empty(), "utf-8")).alias("own_crc"), F.col("doc_id").alias("own_id"), F.struct("*").alias("row"))
    out = keyed.join(once, F.col("own_id").eqNullSafe(F.col("id")) & (F.col("own_crc") == F.col("text_crc32"))).select("at", "row")
    ordered = out.repartitionByRange("at.shard", "at.slot").sortWithinPartitions("at.shard", "at.slot")
    ordered.select("row.*", F.col("at.shard").alias(shard_name), F.col("at.slot").alias(slot_name)).write.partitionBy(shard_name).parquet(path)
    return placed
