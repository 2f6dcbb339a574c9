"""Near-duplicate vectors by counting collisions of one-dimensional projections.

Equal vectors of a label are one vector with a number of copies. Each is projected on ``lines``
random directions. Two vectors collide on a line if either lies in the window of fixed width around
the other there. A pair is verified, by cosine in double precision, if it collides on at least
``least`` lines: window and count are set together from the distance of vectors at the threshold,
so that such a pair is missed with probability below one in a million, by the binomial law.

Which pairs are counted at all: on a further random line through the origin, two vectors at the
threshold lie on the same side with probability p = 1 - acos(cosine) / pi, whatever the data. The sides on k
lines make a bucket, and there are several tables of k lines of their own. k is as large as the number of a
label's vectors asks for, so that an even bucket has about ``block`` of them, and there are as many tables
as p^k asks for, so that a pair at the threshold shares no bucket with probability below ``miss``; small
labels have one bucket and miss nothing. A pair is counted in the first table in which it shares a
bucket, so that numbers of links are exact sums; tasks give out these and the links that connect, not pairs.
A bucket of more than ``block`` vectors is cut in blocks, and every pair of its blocks is a task.

Work grows with tables times vectors times ``block``: a power of about 1.2 of a label's vectors, and the
square only within a bucket that lines do not part, as of one dense cloud, where most pairs are links.

Edge cases. Vectors that are null, empty, zero or have null or non-finite components, and those
with a null label, link with nothing and are kept. Vectors of other lengths link with nothing of this
length. Copies link with each other. Repeated and null identifiers are separate rows. An empty table gives an
empty result. Extra columns are not read.
"""

from __future__ import annotations

from math import acos, ceil, comb, log, log2, pi, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm.common import BROADCAST_ROWS, bounded_broadcast, connected_components, durable

COSINE = 0.93
LINES = 24
#: Half the width of a window, in standard deviations of a pair at the threshold.
HALF_WIDTH = 1.6
MISS = 1e-6
#: Probability that a pair at the threshold shares no bucket, and the most tables made for it.
TABLE_MISS = 1e-4
TABLES = 64
BLOCK = 1024


def least_collisions(lines: int = LINES, half_width: float = HALF_WIDTH, miss: float = MISS) -> int:
    """The largest count that a pair at the threshold reaches with probability above 1 - miss."""
    from math import erf

    p, below = erf(half_width / sqrt(2)), 0.0
    for n in range(lines + 1):
        below += comb(lines, n) * p**n * (1 - p) ** (lines - n)
        if below > miss:
            return n
    return lines


def directions(size: int, lines: int, seed: int = 17) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((size, lines))


def tables_for(n: int, cosine: float, block: int, miss: float = TABLE_MISS, most: int = TABLES) -> tuple[int, int]:
    """(k, tables) for a label of n vectors: the lines of a bucket, and how many tables a pair at the threshold asks for."""
    side = 1 - acos(cosine) / pi
    for k in range(max(0, ceil(log2(max(1, n) / block))), 0, -1):
        tables = ceil(log(miss) / log(1 - side**k))
        if tables <= most:
            return k, tables
    return 0, 1


def bucket_codes(v: np.ndarray, k: int, tables: int) -> np.ndarray:
    """The bucket of each vector in each table: a bit for the side on each of k lines."""
    if not k:
        return np.zeros((len(v), 1), np.int32)
    side = v @ directions(v.shape[1], k * tables, seed=29) >= 0
    return (side.reshape(len(v), tables, k) << np.arange(k)).sum(axis=2).astype(np.int32)


def collision_counts(a: np.ndarray, b: np.ndarray, half: float) -> np.ndarray:
    """Lines on which rows of ``a`` and ``b`` (projections) lie within ``half`` of each other.

    On each line ``b`` is sorted, and the window of each row of ``a`` is a run of it; runs are added
    as differences at their ends, so that a line costs no more than its sort and one pass.
    """
    counts = np.zeros((len(a), len(b)), np.uint8)
    for k in range(a.shape[1]):
        order = np.argsort(b[:, k], kind="stable")
        line = b[order, k]
        low, high = np.searchsorted(line, a[:, k] - half), np.searchsorted(line, a[:, k] + half, side="right")
        place = np.empty(len(b), np.int32)
        place[order] = np.arange(len(b), dtype=np.int32)
        counts += (place >= low[:, None].astype(np.int32)) & (place < high[:, None].astype(np.int32))
    return counts


def _valid(name: str):
    bad = F.exists(name, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.col(name).isNotNull() & ~bad & F.exists(name, lambda x: x != 0)


def vector_links(rows: DataFrame, cosine: float = COSINE, lines: int = LINES, half_width: float = HALF_WIDTH, block: int = BLOCK, miss: float = TABLE_MISS, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """vec_id, n_links, component_id and kept of every row of ``rows`` (vec_id, embedding, label)."""
    least = least_collisions(lines, half_width)
    deviation = sqrt(2 - 2 * cosine)
    half = half_width * deviation
    base = rows.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"), F.monotonically_increasing_id().alias("row_no"))
    base = base.withColumn("ok", F.coalesce(_valid("v") & F.col("label").isNotNull(), F.lit(False)))
    base = durable(base.withColumn("key", F.when(F.col("ok"), F.xxhash64("label", "v"))), "vectors")
    # one vector for all its copies; the key is checked by the vector itself
    distinct = base.where("ok").groupBy("label", "v").agg(F.count(F.lit(1)).alias("copies"), F.min("row_no").alias("node"), F.min("vec_id").alias("first"))

    kind = "float" if dict(rows.dtypes)["embedding"] == "array<float>" else "double"
    distinct = durable(distinct.select("label", F.col("v").cast(f"array<{kind}>").alias("v"), F.size("v").alias("dim"), "copies", "node"), "distinct")
    sizes = distinct.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("n"))

    def dealt(batches):
        """A row for each vector and table, with its buckets in all tables."""
        for batch in batches:
            number, size = batch.column("n").to_numpy(), batch.column("dim").to_numpy()
            start = batch.column("v").offsets.to_numpy()[:-1]
            flat = batch.column("v").values.to_numpy()
            for n, d in {(int(x), int(y)) for x, y in zip(number, size, strict=True)}:
                own = np.flatnonzero((number == n) & (size == d))
                x = flat[start[own][:, None] + np.arange(d)].astype(np.float64)
                codes = bucket_codes(x, *tables_for(n, cosine, block, miss))
                for t in range(codes.shape[1]):
                    part = batch.take(pa.array(own)).drop_columns(["n"])
                    part = part.append_column("t", pa.array(np.full(len(own), t, np.int32))).append_column("code", pa.array(codes[:, t]))
                    yield part.append_column("codes", pa.array([c.tobytes() for c in codes], pa.binary()))

    known = distinct.join(bounded_broadcast(sizes, sizes.count(), broadcast_rows), ["label", "dim"]).select("label", "v", "dim", "copies", "node", "n")
    bucket = ["label", "dim", "t", "code"]
    spread = known.mapInArrow(dealt, f"label {dict(distinct.dtypes)['label']}, v array<{kind}>, dim int, copies bigint, node bigint, t int, code int, codes binary")
    large = durable(spread.groupBy(*bucket).agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("u")).where("u > 1"), "large")
    cut = spread.join(bounded_broadcast(large, large.count(), broadcast_rows), bucket, "left").withColumn("u", F.coalesce("u", F.lit(1)))
    cut = cut.withColumn("block", F.pmod(F.xxhash64("node"), F.col("u")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("u") - 1)))
    work = cut.select(*bucket, F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "copies", "v", "codes")

    def in_pair(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        place = table.column("block").to_numpy()
        node, copies = table.column("node").to_numpy(), table.column("copies").to_numpy()
        v = table.column("v").combine_chunks()
        v = np.asarray(v.flatten()).reshape(len(node), -1).astype(np.float64)
        codes, t = np.frombuffer(b"".join(table.column("codes").to_pylist()), np.int32).reshape(len(node), -1), table.column("t")[0].as_py()
        unit = v / np.linalg.norm(v, axis=1, keepdims=True)
        on_lines = unit @ directions(v.shape[1], lines)
        a, b = np.flatnonzero(place == i), np.flatnonzero(place == j)
        counts = collision_counts(on_lines[a], on_lines[b], half)
        x, y = np.nonzero(counts >= least)
        if i == j:
            x, y = x[x < y], y[x < y]
        x, y = a[x], b[y]
        near = np.einsum("ij,ij->i", unit[x], unit[y]) >= cosine if len(x) else np.zeros(0, bool)
        x, y = x[near], y[near]
        # a table before this one has had a pair that shares a bucket there
        fresh = ~(codes[x, :t] == codes[y, :t]).any(axis=1)
        x, y = x[fresh], y[fresh]
        links = np.bincount(x, copies[y], len(node)) + np.bincount(y, copies[x], len(node))
        root, out = np.arange(len(node)), []
        for s, t in zip(x, y, strict=True):
            if root[s] != root[t]:
                root[root == root[t]] = root[s]
                out.append((node[s], node[t]))
        some = np.flatnonzero(links)
        nodes = np.concatenate([node[some], np.array([s for s, _ in out], np.int64)])
        others = [None] * len(some) + [int(t) for _, t in out]
        number = np.concatenate([links[some], np.zeros(len(out))]).astype(np.int64)
        return pa.table({"node": pa.array(nodes, pa.int64()), "other": pa.array(others, pa.int64()), "n": pa.array(number, pa.int64())})

    found = durable(work.groupBy(*bucket, "i", "j").applyInArrow(in_pair, "node bigint, other bigint, n bigint"), "found")
    links = found.where("other is not null").select(F.col("node").alias("a"), F.col("other").alias("b"))
    touched = links.select(F.col("a").alias("v")).union(links.select(F.col("b").alias("v"))).distinct()
    roots = durable(connected_components(touched, links, "vec").withColumnRenamed("v", "n_id"), "roots")
    degrees = found.where("other is null").groupBy("node").agg(F.sum("n").alias("n"))
    heads = base.where("ok").groupBy("label", "v", "key").agg(F.count(F.lit(1)).alias("copies"), F.min("row_no").alias("node"), F.min("vec_id").alias("first"))
    heads = heads.join(degrees, "node", "left").join(roots, F.col("node") == F.col("n_id"), "left")
    heads = durable(heads.where("copies > 1 or n is not null").select("key", "label", "v", "node", "copies", "first", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("root", "node").alias("root")), "heads")
    least_of = heads.groupBy("root").agg(F.min("first").alias("component_id"))
    lookup = heads.join(least_of, "root").select(F.col("key").alias("k"), F.col("label").alias("l"), F.col("v").alias("w"), (F.col("n") + F.col("copies") - 1).alias("n_links"), "component_id")
    lookup = durable(lookup, "lookup")
    lookup = bounded_broadcast(lookup, lookup.count(), broadcast_rows // 50)
    out = base.join(lookup, (F.col("key") == F.col("k")) & (F.col("label") == F.col("l")) & (F.col("v") == F.col("w")), "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), F.when(F.col("n_links").isNull(), F.col("vec_id")).otherwise(F.col("component_id")).alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
