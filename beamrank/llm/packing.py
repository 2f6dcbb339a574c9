"""Best-fit packing planned over a histogram of lengths.

Texts are tokenised once into pieces of at most ``capacity`` ids. The driver sees only how many
pieces have each length (at most ``capacity`` counts) and runs best-fit decreasing over counts:
sequences with the same room left are one entry, and all pieces of a length that go to such
sequences are one step. The plan is a table of steps; a piece finds its step by its length and its
rank among pieces of that length. Ranks are taken within salted parts of a length, after the counts
of the parts before, so that a length that most pieces have is no hot key.

Edge cases. A null text is empty; an empty text is the end id alone. Only longer documents are cut:
the first piece has what remains, all others are full. Repeated rows are separate documents. An
empty table gives an empty result. Extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections import defaultdict, deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm import textkit
from beamrank.llm.common import bounded_broadcast, durable
from beamrank.llm.tokens import SLICE_BYTES, encoder, vocabulary

CAPACITY = 2048
END_ID = 0
VOCABULARY = "byte_bpe_50k.json"
#: Steps of a plan that may be broadcast.
PLAN_ROWS = 500_000

PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


def tokenized_pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary_path: str | None = None, with_ids: bool = False) -> DataFrame:
    """Pieces of each document: doc_id, piece, start, length, ids_crc32, and ids on request."""
    path = vocabulary_path or vocabulary(VOCABULARY)

    def run(batches):
        code = encoder(path)
        for batch in batches:
            for part in textkit.slices(batch, "text", SLICE_BYTES):
                ids, bounds = code.encode(part.column(1))
                yield _pieces(part.column(0), ids, bounds, capacity, end_id, with_ids)

    return docs.select("doc_id", "text").mapInArrow(run, PIECES + (", ids array<int>" if with_ids else ""))


def _pieces(doc_ids: pa.Array, ids: np.ndarray, bounds: np.ndarray, capacity: int, end_id: int, with_ids: bool) -> pa.RecordBatch:
    doc, number, start, length, crc, tokens = [], [], [], [], [], []
    for d in range(len(doc_ids)):
        own = np.append(ids[bounds[d] : bounds[d + 1]], np.uint32(end_id)).astype("<u4")
        first = (len(own) - 1) % capacity + 1
        cuts = [0, *range(first, len(own) + 1, capacity)]
        for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
            doc.append(d)
            number.append(k)
            start.append(a)
            length.append(b - a)
            crc.append(zlib.crc32(own[a:b].tobytes()))
            if with_ids:
                tokens.append(own[a:b])
    columns = [doc_ids.take(pa.array(doc, pa.int64())), pa.array(number, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))]
    names = ["doc_id", "piece", "start", "length", "ids_crc32"]
    if with_ids:
        columns.append(pa.array(tokens, pa.list_(pa.int32())))
        names.append("ids")
    return pa.record_batch(columns, names)


def plan_best_fit(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Steps (length, rank from, rank to, first sequence, pieces a sequence, offset), and sequences.

    Lengths go from the longest. A piece goes to the sequence with the least room in which it fits,
    and that one is then the tightest for the next of its length: so a sequence takes all it can
    hold of a length before the next sequence is looked at.
    """
    rooms: dict[int, deque[tuple[int, int]]] = defaultdict(deque)  # room left -> runs of sequences
    steps, made = [], 0
    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        for room in sorted(r for r in rooms if r >= length and rooms[r]):
            each = room // length
            while left and rooms[room]:
                first, n = rooms[room].popleft()
                whole = min(n, left // each)
                if whole:
                    steps.append((length, rank, rank + whole * each, first, each, capacity - room))
                    rooms[room - each * length].append((first, whole))
                    rank, left = rank + whole * each, left - whole * each
                if whole < n and left and left < each:
                    steps.append((length, rank, rank + left, first + whole, each, capacity - room))
                    rooms[room - left * length].append((first + whole, 1))
                    rank, left, whole = rank + left, 0, whole + 1
                if whole < n:
                    rooms[room].appendleft((first + whole, n - whole))
            if not left:
                break
        if left:
            each = capacity // length
            whole, rest = divmod(left, each)
            steps.append((length, rank, rank + left, made, each, 0))
            if whole:
                rooms[capacity - each * length].append((made, whole))
            if rest:
                rooms[capacity - rest * length].append((made + whole, 1))
            made += whole + bool(rest)
    return steps, made


def place_pieces(pieces: DataFrame, capacity: int = CAPACITY, plan_rows: int = PLAN_ROWS) -> DataFrame:
    """``pieces`` (a stored table) with sequence_id and offset."""
    spark = pieces.sparkSession
    histogram = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}
    steps, _ = plan_best_fit(histogram, capacity)
    names = ["step_length", "rank_from", "rank_to", "first_sequence", "each", "base"]
    columns = list(zip(*steps, strict=True)) if steps else [[] for _ in names]
    plan = spark.createDataFrame(pa.table({n: pa.array(c, pa.int64()) for n, c in zip(names, columns, strict=True)}))
    plan = bounded_broadcast(plan, len(steps), plan_rows)
    salts = min(8192, max(16, sum(histogram.values()) // 1_000_000))
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)).cast("int"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    counts = salted.groupBy("length", "salt").count()
    counts = counts.select("length", "salt", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    inside = Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "start")
    ranked = salted.withColumn("place", F.row_number().over(inside) - 1)
    ranked = ranked.join(bounded_broadcast(counts, len(histogram) * salts), ["length", "salt"]).withColumn("rank", F.col("first") + F.col("place"))
    on = (F.col("length") == F.col("step_length")) & (F.col("rank") >= F.col("rank_from")) & (F.col("rank") < F.col("rank_to"))
    nth = F.col("rank") - F.col("rank_from")
    return (
        ranked.join(plan, on)
        .withColumn("sequence_id", F.expr("first_sequence + (rank - rank_from) div each"))
        .withColumn("offset", F.col("base") + (nth % F.col("each")) * F.col("length"))
        .select(*pieces.columns, "sequence_id", "offset")
    )


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary_path: str | None = None) -> DataFrame:
    """Where every piece of every document goes: the pieces' digests with sequence_id and offset."""
    return place_pieces(durable(tokenized_pieces(docs, capacity, end_id, vocabulary_path), "pieces"), capacity)


def packed_sequences(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary_path: str | None = None) -> DataFrame:
    """The sequences themselves: sequence_id, ids, and the documents of their pieces in order."""
    pieces = durable(tokenized_pieces(docs, capacity, end_id, vocabulary_path, with_ids=True), "pieces")
    placed = place_pieces(pieces, capacity)
    parts = placed.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "doc_id", "ids"))).alias("parts"))
    return parts.select("sequence_id", F.flatten(F.col("parts.ids")).alias("ids"), F.col("parts.doc_id").alias("doc_ids"))
