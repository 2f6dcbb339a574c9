"""Quality classifier: histogram gradient-boosted trees over statistics of whole texts.

Statistics are taken once for every document and stored. Trees are grown on the driver from at most
``sample_rows`` labelled rows (a documented bound; chosen by a hash of the identifier, so that a
larger corpus gives a sample of the same size), over quantile bins with gradient and Hessian sums.
They are flattened into arrays and traversed for all rows and trees at once.

Edge cases. Null and empty texts have statistics of zero words and get a score like any other. Null
labels are not learnt from; of several labels of a document the mean decides. Without any labelled
row every score is 0.5. Repeated rows score alike. An empty table gives an empty result. Extra
columns are not read; ``keep_good`` passes them through.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from beamrank.llm import textkit
from beamrank.llm.common import durable

#: The most labelled rows that a model is fitted on, about.
SAMPLE_ROWS = 50_000
THRESHOLD = 0.3
#: Narrow enough for the arrays of a slice to stay small.
SLICE_BYTES = 2 << 20
TREES, DEPTH, BINS, RATE, L2 = 60, 4, 64, 0.2, 1.0

FEATURES = [
    "log_bytes", "log_words", "word_bytes", "upper", "digits", "signs", "marks", "not_ascii", "lines",
    "distinct_words", "repeats", "distinct_pairs", "capital_words", "signed_words", "lone_signs", "long_words",
]

_CLASS = np.zeros((256, 5), np.uint8)
_CLASS[ord("A") : ord("Z") + 1, 0] = 1
_CLASS[ord("0") : ord("9") + 1, 1] = 1
for _c in map(ord, "#$%&*|@^~<>{}[]\\/=+_"):
    _CLASS[_c, 2] = 1
for _c in map(ord, "!?.,;:'\"()-"):
    _CLASS[_c, 3] = 1
_CLASS[128:, 4] = 1
_ODD = (_CLASS[:, 2] | (np.arange(256) == ord("!"))).astype(bool)


def _sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[offsets[1:]] - total[offsets[:-1]]


#: Sums over a text, in this order; FEATURES are made of them.
_SIZE, _WORDS, _CLASSES, _LINES, _DISTINCT, _SAME, _PAIRS, _CAPITAL, _SIGNED, _LONE, _LONG = 0, 1, slice(2, 7), 7, 8, 9, 10, 11, 12, 13, 14


def text_statistics(column: pa.Array, window: int = textkit.WINDOW_BYTES) -> np.ndarray:
    """One row of FEATURES for each text, from sums over windows of at most ``window`` bytes.

    Of a text that lies in several windows, the last word is carried on, and its distinct words and
    pairs are gathered as sorted hashes.
    """
    sums = np.zeros((len(column), 15))
    carried: dict[int, np.uint64] = {}
    gathered: dict[tuple[int, int], np.ndarray] = {}
    for first, buf, offsets in textkit.windows(column, window):
        n = len(offsets) - 1
        part = sums[first : first + n]
        part[:, _SIZE] += np.diff(offsets)
        for k in range(5):
            part[:, 2 + k] += _sums(_CLASS[buf, k], offsets)
        part[:, _LINES] += _sums(buf == 10, offsets)
        begin, end, doc = textkit.words(buf, offsets)
        if not len(begin):
            continue
        count = np.bincount(doc, minlength=n)
        word_at = np.concatenate([[0], np.cumsum(count)])
        hashes = textkit.span_hashes(buf, begin, end)
        part[:, _WORDS] += count
        before = np.concatenate([[np.uint64(0)], hashes[:-1]])
        has = np.concatenate([[False], doc[1:] == doc[:-1]])
        if int(doc[0]) == 0 and first in carried:
            before[0], has[0] = carried.pop(first), True
        salt = textkit.mix64(doc.astype(np.uint64) + np.uint64(1))
        pairs = textkit.mix64(before * np.uint64(3) + hashes)
        # texts that go on beyond this window, or came from the one before
        for d in {0, n - 1}:
            open_end = first + d in {k for k, _ in gathered} or (d == n - 1 and offsets[-1] == len(buf) and sums[first + d, _SIZE] < _size_of(column, first + d))
            if open_end:
                own = slice(word_at[d], word_at[d + 1])
                for k, values in ((_DISTINCT, hashes[own]), (_PAIRS, pairs[own][has[own]])):
                    gathered[first + d, k] = np.unique(np.concatenate([gathered.get((first + d, k), np.empty(0, np.uint64)), values]))
                if count[d]:
                    carried[first + d] = hashes[own][-1]
        part[:, _DISTINCT] += _distinct(hashes ^ salt, doc, n)
        part[:, _PAIRS] += _distinct((pairs ^ salt)[has], doc[has], n)
        part[:, _SAME] += _sums(has & (before == hashes), word_at)
        head, odd, size = buf[begin], _ODD[buf[end - 1]], end - begin
        part[:, _CAPITAL] += _sums((head >= 65) & (head <= 90), word_at)
        part[:, _SIGNED] += _sums(odd, word_at)
        part[:, _LONE] += _sums(odd & (size == 1), word_at)
        part[:, _LONG] += _sums(size > 20, word_at)
    for (d, k), values in gathered.items():
        sums[d, k] = len(values)
    out = np.zeros((len(column), len(FEATURES)), np.float32)
    size, count = sums[:, _SIZE], sums[:, _WORDS]
    n, w = np.maximum(size, 1)[:, None], np.maximum(count, 1)[:, None]
    out[:, 0], out[:, 1], out[:, 2] = np.log1p(size), np.log1p(count), size / w[:, 0]
    out[:, 3:8] = sums[:, _CLASSES] / n
    out[:, 8:] = sums[:, _LINES:] / w
    return out


def _size_of(column: pa.Array, row: int) -> int:
    return pc.binary_length(column.slice(row, 1))[0].as_py() or 0


def _distinct(values: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    order = np.argsort(values, kind="stable")
    values, doc = values[order], doc[order]
    new = np.ones(len(values), bool)
    new[1:] = values[1:] != values[:-1]
    return np.bincount(doc[new], minlength=n)


@dataclass
class Forest:
    """Complete trees of one depth as arrays: inner nodes in level order, then leaves."""

    feature: np.ndarray
    threshold: np.ndarray
    leaf: np.ndarray
    base: float

    def score(self, x: np.ndarray) -> np.ndarray:
        rows, trees = np.arange(len(x))[:, None], np.arange(len(self.leaf))[None, :]
        at = np.zeros((len(x), len(self.leaf)), np.int32)
        for _ in range(int(np.log2(self.leaf.shape[1])) if self.leaf.size else 0):
            at = 2 * at + 1 + (x[rows, self.feature[trees, at]] > self.threshold[trees, at])
        values = self.leaf[trees, at - self.feature.shape[1]].sum(axis=1) if self.leaf.size else 0.0
        return 1 / (1 + np.exp(-(self.base + values * np.ones(len(x)))))


def fit_forest(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, bins: int = BINS, rate: float = RATE, l2: float = L2) -> Forest:
    inner, leaves = 2**depth - 1, 2**depth
    if not len(y):
        return Forest(np.zeros((0, inner), np.int32), np.zeros((0, inner)), np.zeros((0, leaves)), 0.0)
    mean = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    base = float(np.log(mean / (1 - mean)))
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(edges)], axis=1)
    n_features = x.shape[1]
    feature, threshold = np.zeros((trees, inner), np.int32), np.full((trees, inner), np.inf)
    leaf, margin = np.zeros((trees, leaves)), np.full(len(y), base)
    for t in range(trees):
        p = 1 / (1 + np.exp(-margin))
        gradient, hessian, at = p - y, p * (1 - p), np.zeros(len(y), np.int64)
        for level in range(depth):
            nodes, first = 2**level, 2**level - 1
            cell = ((at - first)[:, None] * n_features + np.arange(n_features)) * bins + binned
            g = np.bincount(cell.ravel(), np.repeat(gradient, n_features), nodes * n_features * bins).reshape(nodes, n_features, bins).cumsum(axis=2)
            h = np.bincount(cell.ravel(), np.repeat(hessian, n_features), nodes * n_features * bins).reshape(nodes, n_features, bins).cumsum(axis=2)
            all_g, all_h = g[:, :, -1:], h[:, :, -1:]
            gain = g**2 / (h + l2) + (all_g - g) ** 2 / (all_h - h + l2) - all_g**2 / (all_h + l2)
            gain[(h < 1e-2) | (all_h - h < 1e-2)] = 0
            best = gain.reshape(nodes, -1).argmax(axis=1)
            for k in range(nodes):
                f, b = divmod(int(best[k]), bins)
                if gain[k, f, b] > 1e-6 and b < len(edges[f]):
                    feature[t, first + k], threshold[t, first + k] = f, edges[f][b]
            at = 2 * at + 1 + (x[np.arange(len(y)), feature[t, at]] > threshold[t, at])
        g, h = np.bincount(at - inner, gradient, leaves), np.bincount(at - inner, hessian, leaves)
        leaf[t] = -rate * g / (h + l2)
        margin += leaf[t, at - inner]
    return Forest(feature, threshold, leaf, base)


def statistics_table(docs: DataFrame) -> DataFrame:
    """doc_id and the statistics of every document, stored."""

    def run(batches):
        for batch in batches:
            for part in textkit.slices(batch, "text", SLICE_BYTES):
                x = text_statistics(part.column(1))
                yield pa.record_batch([part.column(0), *(pa.array(x[:, k]) for k in range(x.shape[1]))], ["doc_id", *FEATURES])

    schema = "doc_id bigint, " + ", ".join(f"{f} float" for f in FEATURES)
    return durable(docs.select("doc_id", "text").mapInArrow(run, schema), "statistics")


def fold_of(doc_id, parts: int):
    """crc32 of the identifier as text, by the number of folds; null identifiers count as empty."""
    return F.crc32(F.encode(F.coalesce(F.col(doc_id).cast("string"), F.lit("")), "utf-8")) % parts


def labelled(labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id and y of labelled documents outside the held-out fold: about ``sample_rows`` of them at most, chosen by hash."""
    known = labels.where("quality is not null and doc_id is not null").groupBy("doc_id").agg(F.avg("quality").alias("mean"))
    known = durable(known.where(fold_of("doc_id", 5) != 0).select("doc_id", (F.col("mean") >= 0.5).cast("int").alias("y")), "labelled")
    n = known.count()
    return known if n <= sample_rows else known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(1_000_000 * sample_rows / n))


def train(statistics: DataFrame, known: DataFrame, sample_rows: int = SAMPLE_ROWS) -> Forest:
    """Fit on rows of labelled identifiers; of an identifier with many rows, one for each of their distinct statistics up to a bound.

    The labelled side is bounded, so that it is broadcast and the statistics of all documents do not move.
    """
    rows = statistics.join(F.broadcast(known), "doc_id").groupBy("doc_id", *FEATURES).agg(F.first("y").alias("y"))
    rows = rows.orderBy("doc_id", *FEATURES).limit(2 * sample_rows).toPandas()
    return fit_forest(rows[FEATURES].to_numpy(np.float32), rows["y"].to_numpy(np.float64))


def score_documents(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    statistics = statistics_table(docs)
    forest = train(statistics, labelled(labels, sample_rows), sample_rows)

    def run(batches):
        for batch in batches:
            x = np.stack([batch.column(k + 1).to_numpy(zero_copy_only=False) for k in range(len(FEATURES))], axis=1)
            yield pa.record_batch([batch.column(0), pa.array(forest.score(x).astype(np.float64))], ["doc_id", "score"])

    scored = statistics.mapInArrow(run, "doc_id bigint, score double")
    return scored.select("doc_id", (fold_of("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """Documents that are predicted good, with all their columns. Texts pass each worker once and are not moved."""
    known = labelled(labels, sample_rows)
    forest = train(statistics_table(docs.join(F.broadcast(known), "doc_id", "left_semi")), known, sample_rows)
    place = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            for part in textkit.slices(batch, batch.schema.names[place], SLICE_BYTES):
                yield part.filter(pa.array(forest.score(text_statistics(part.column(place))) >= threshold))

    # names of no meaning on the way, so that any name of the user's will do
    plain = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])
    return plain.mapInArrow(run, plain.schema).toDF(*docs.columns)
