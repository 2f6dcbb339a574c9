"""Interpolated modified Kneser-Ney model of any order, counted in Spark and memory-mapped to score.

1. Words are counted as 64-bit hashes. The distinct ones, in order of hash, make the vocabulary; the
   place of a word is its number. A hash range is a file.
2. Runs of two words are counted as (number before, number) in each task, in wider keys beyond 32 bits of numbers,
   and sent on as sorted, compressed arrays, not as rows. A bucket is a range of contexts; a context
   that has more than an eighth of a bucket's share of all tokens is spread over all buckets by its second
   half. Each bucket merges what it gets into a file that has, for each context of its range, where its
   words begin, and the words in as few bytes as their numbers need. The place of a run in these files is its
   number, so that a run of one word more is again a pair: the number of the run before, and a word.
   Levels are counted so, up to ``order`` words.
3. Buckets also give out how many different words come before each run of the level below, as packed runs for
   each file there, which are the values there. Values take one byte, what follows a context two; the few that
   need more stand apart in the same file. Sums of contexts that are spread go by rows.
4. Each worker maps the files and looks up the distinct words and runs of a window of texts in order.

The highest order has discounted counts; lower ones have numbers of different words before, also
discounted, and what single words leave goes evenly to all words and the unknown one. The start of a text
is a context like a word; after an unknown context the order below scores alone. Training reads all
rows given; nothing is pruned, and texts are read in windows, so that a long one needs no more memory.

Files lie in the shared folder under the name of the attempt that wrote them, and are used only if
reported. Tables and shuffles of a level go when it is done. A worker that cannot map the store itself copies a file, maps it and removes the name at once.

Edge cases. Null is empty; an empty text is the end token alone. Repeated rows count twice. With no
training rows every word is unknown. An empty table gives an empty result. Extra columns are not read.
"""

from __future__ import annotations

import gc
import os
import struct
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from beamrank.llm import textkit
from beamrank.llm.common import durable, release_scratch, scratch_path, scratch_scope, text_or_empty
from beamrank.llm.quality import fold_of

#: Words in a file of the vocabulary, and tokens for which there is one bucket of pairs.
RANGE_WORDS = 250_000
BUCKET_TOKENS = 8_000_000
#: Words of a run in the highest level, unless a caller asks for more; the query does.
ORDER = 2
#: Entries that a task gathers before it gives out a run.
RUN_ENTRIES = 1_000_000
SLICE_BYTES = 2 << 20
#: The most words whose numbers, and that of the start, fit 32 bits.
NARROW_WORDS = (1 << 32) - 2
_SPREAD = np.uint64(0x9E3779B97F4A7C15)
END = np.uint64(0x5E4D0F7A11E4D0F7)
START = np.uint64(0x57A47C0DE57A47C1)


def token_windows(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Hashes of the lower-case words of all texts, each text ended by END, with the text of each and the hash before it.

    They come in windows of so many bytes; START is before a text's first token, and what is before a
    window's first token is carried over.
    """
    size = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends, low, carried = np.cumsum(size), 0, START
    for first, buf, offsets in textkit.windows(column, limit):
        low += len(buf)
        buf = textkit.LOWER[buf]
        begin, end, doc = textkit.words(buf, offsets)
        here = np.arange(first, first + len(offsets) - 1)
        over = here[(size[here] > 0) & (ends[here] <= low)]
        over = over[ends[over] > low - len(buf)]
        doc = np.concatenate([doc + first, over])
        order = np.argsort(doc, kind="stable")
        doc, token = doc[order], np.concatenate([textkit.span_hashes(buf, begin, end), np.full(len(over), END)])[order]
        if not len(doc):
            continue
        before = np.concatenate([[carried], token[:-1]])
        before[1:][doc[1:] != doc[:-1]] = START
        carried = token[-1] if token[-1] != END or ends[doc[-1]] > low else START
        yield token, doc, before
    empty = np.flatnonzero(size == 0)
    if len(empty):
        yield np.full(len(empty), END), empty, np.full(len(empty), START)


def _merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    key, count = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(key, kind="stable")
    key, count = key[order], count[order]
    new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.empty(0, np.int64)
    return key[new], np.add.reduceat(count, new) if len(new) else count


def _all_windows(batches):
    for batch in batches:
        for part in textkit.slices(batch, "text", SLICE_BYTES):
            yield from token_windows(part.column("text"))


def _gathered(arrays: Iterator[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Merged (keys, counts) of the arrays of a task, given out whenever they are many."""
    keys, counts, size = [], [], 0
    for array in arrays:
        key, count = np.unique(array, return_counts=True)
        keys.append(key)
        counts.append(count.astype(np.int64))
        size += len(key)
        if size > RUN_ENTRIES:
            merged = _merge(keys, counts)
            keys, counts, size = [merged[0]], [merged[1]], len(merged[0])
            if size > RUN_ENTRIES // 2:
                yield merged
                keys, counts, size = [], [], 0
    if size:
        yield _merge(keys, counts)


def _write(folder: str, name: str, *arrays: np.ndarray) -> str:
    store, place = fs.FileSystem.from_uri(folder)
    name = f"{name}-{uuid.uuid4().hex[:12]}.bin"
    with store.open_output_stream(f"{place}/{name}") as out:
        for a in arrays:
            out.write(np.ascontiguousarray(a).tobytes())
    return f"{folder}/{name}"


def _write_counted(folder: str, name: str, key: np.ndarray, count: np.ndarray) -> str:
    """Sorted keys and their counts, as wide as the largest of the file needs; the name tells both widths."""
    width = 4 if not len(count) or count.max() < 1 << 32 else 8
    return _write(folder, f"{name}-{key.dtype.itemsize}-{width}", key if key.dtype.kind == "S" else key.astype("<u8"), count.astype(f"<u{width}"))


def _counted(path: str) -> list[np.ndarray]:
    _, of_key, of_count, *_ = path.rpartition("/")[2].split("-")
    return _columns(path, "<u8" if of_key == "8" else "S16", f"<u{of_count}")


_maps: dict[str, np.ndarray] = {}


def mapped(path: str) -> np.ndarray:
    """The bytes of a file, memory-mapped once in this worker."""
    if path not in _maps:
        if len(_maps) > 4096:
            _maps.clear()
        store, place = fs.FileSystem.from_uri(path)
        if isinstance(store, fs.LocalFileSystem):
            _maps[path] = np.memmap(place, np.uint8, "r").view(np.ndarray)
        else:
            with tempfile.NamedTemporaryFile(delete=False) as copy, store.open_input_stream(place) as source:
                while chunk := source.read(8 << 20):
                    copy.write(chunk)
            _maps[path] = np.memmap(copy.name, np.uint8, "r").view(np.ndarray)
            os.unlink(copy.name)
    return _maps[path]


def _columns(path: str, *kinds: str) -> list[np.ndarray]:
    raw, at = mapped(path), 0
    n = len(raw) // sum(np.dtype(k).itemsize for k in kinds)
    out = []
    for k in kinds:
        size = n * np.dtype(k).itemsize
        out.append(raw[at : at + size].view(k))
        at += size
    return out


def _find(array: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Places of sorted ``keys`` in a sorted array, -1 where absent."""
    if not len(array) or not len(keys):
        return np.full(len(keys), -1)
    at = np.minimum(np.searchsorted(array, keys), len(array) - 1)
    return np.where(array[at] == keys, at, -1)


@dataclass
class Vocabulary:
    """Files of hash ranges; ``first`` is the number of the first word of each."""

    bits: int
    paths: list[str | None]
    first: list[int]
    size: int
    tokens: int

    def numbers(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number (-1: unknown) and training count of sorted distinct hashes."""
        number, count = np.full(len(hashes), -1, np.int64), np.zeros(len(hashes), np.int64)
        part = (hashes >> np.uint64(64 - self.bits)).astype(np.int64) if self.bits else np.zeros(len(hashes), np.int64)
        edges = np.searchsorted(part, np.arange(len(self.paths) + 1))
        for k in np.unique(part):
            if self.paths[k]:
                key, n = _counted(self.paths[k])
                own = slice(edges[k], edges[k + 1])
                at = _find(key, hashes[own])
                hit = at >= 0
                number[own] = np.where(hit, at + self.first[k], -1)
                count[own] = np.where(hit, n[at], 0)
        return number, count

    def of_window(self, token: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Number and count of every token, and the number of the one before it; the start of a text has the number after the last."""
        distinct, back = np.unique(np.append(token, before[0]), return_inverse=True)
        number, count = self.numbers(distinct)
        number, count = number[back], count[back]
        previous = np.concatenate([number[-1:], number[:-2]])
        previous[before == START] = self.size
        return number[:-1], count[:-1], previous


def _write_values(folder: str, name: str, value: np.ndarray) -> str:
    """One byte for each value; those from 255 on stand apart with their places."""
    over = np.flatnonzero(value >= 255)
    return _write(folder, name, *(np.asarray(a, "<i8") for a in ([len(over)], over, value[over])), np.minimum(value, 255).astype(np.uint8))


def _values_at(path: str, place: np.ndarray) -> np.ndarray:
    raw = mapped(path)
    m = int(raw[:8].view("<i8")[0])
    over, large = raw[8 : 8 + 16 * m].view("<i8").reshape(2, m)
    out = raw[8 + 16 * m :][place].astype(np.int64)
    big = np.flatnonzero(out == 255)
    out[big] = large[np.searchsorted(over, place[big])]
    return out


def _write_figures(folder: str, slots: int, slot: np.ndarray, sums: list[np.ndarray]) -> str:
    """Of the contexts at some slots: the sum of their values, and how many values are 1, 2 and more.

    Sums below 16 have the four figures in four bits each; larger ones stand apart with their slots.
    """
    n, n1, n2, n3 = sums
    code, over = np.zeros(slots, "<u2"), np.flatnonzero(n > 15)
    code[slot] = np.where(n > 15, 65535, (n & 15) | (n1 & 15) << 4 | (n2 & 15) << 8 | (n3 & 15) << 12)
    return _write(folder, "figures", *(np.asarray(a, "<i8") for a in ([len(over)], slot[over], *(x[over] for x in sums))), code)


def _figures_at(path: str, slot: np.ndarray, discounts: tuple[float, float, float], weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What follows a context in all, and the weight that it leaves; ``weights`` has that of each code."""
    raw = mapped(path)
    m = int(raw[:8].view("<i8")[0])
    large = raw[8 : 8 + 40 * m].view("<i8").reshape(5, m)
    code = raw[8 + 40 * m :].view("<u2")[slot]
    n, left = (code & 15).astype(np.int64), weights[code]
    big = np.flatnonzero(code == 65535)
    own = large[1:, np.searchsorted(large[0], slot[big])]
    n[big], left[big] = own[0], _left(own, discounts)
    return n, left


def _left(n: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    return (d[0] * n[1] + d[1] * n[2] + d[2] * n[3]) / np.maximum(n[0], 1)


def _range_first(context: np.ndarray, low: int, slots: int, *arrays: np.ndarray) -> list[np.ndarray]:
    """Arrays in order of context, those of the contexts from ``low`` moved to the front."""
    a, b = np.searchsorted(context, [low, low + slots])
    return [np.concatenate([x[a:b], x[:a], x[b:]]) for x in (context, *arrays)]


#: Contexts that share one wide start, from which theirs are counted.
_BLOCK = 16


def _write_runs(folder: str, name: str, low: int, slots: int, context: np.ndarray, word: np.ndarray) -> str:
    """Words by context, as ``_range_first`` orders them: each context of the range has a slot, and so have others that occur."""
    n = int(np.count_nonzero((context >= low) & (context < low + slots)))
    other, of_other = np.unique(context[n:], return_counts=True)
    starts = np.cumsum([0, *np.bincount(context[:n] - low, minlength=slots), *of_other], dtype=np.int64)
    base = starts[::_BLOCK]
    offset = starts - np.repeat(base, _BLOCK)[: len(starts)]
    narrow = next(w for w in (2, 4, 8) if offset.max() < 1 << 8 * w)
    width = max(1, -(-int(word.max(initial=0)).bit_length() // 8))
    head = np.array([slots, len(other), len(word), narrow, width, len(base)], "<i8")
    letters = word.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]
    return _write(folder, name, head, base.astype("<i8"), other.astype("<i8"), offset.astype(f"<u{narrow}"), letters, np.zeros(8, np.uint8))


class Runs:
    """A mapped file of ``_write_runs``; ``low`` is the first context of its range."""

    def __init__(self, path: str, low: int):
        raw = mapped(path)
        self.low = low
        self.slots, others, n, narrow, width, blocks = (int(x) for x in raw[:48].view("<i8"))
        at = 48 + 8 * blocks
        self._base, self.others = raw[48:at].view("<i8"), raw[at : at + 8 * others].view("<i8")
        at += 8 * others
        end = at + narrow * (self.slots + others + 1)
        self._offset = raw[at:end].view(f"<u{narrow}")
        self._raw = np.ndarray((n,), "<u4" if width <= 4 else "<u8", buffer=raw, offset=end, strides=(width,))
        self._mask = (1 << 8 * width) - 1

    def words(self, place: np.ndarray) -> np.ndarray:
        return self._raw[place].astype(np.int64) & self._mask if self._mask < 1 << 63 else self._raw[place].astype(np.int64)

    def _starts(self, slot: np.ndarray) -> np.ndarray:
        return self._base[slot // _BLOCK] + self._offset[slot].astype(np.int64)

    def contexts(self) -> np.ndarray:
        """Of each place."""
        each = np.concatenate([np.arange(self.low, self.low + self.slots), self.others])
        return np.repeat(each, np.diff(self._starts(np.arange(len(each) + 1))))

    def find(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Places, -1 where absent; by halves within the words of the context."""
        slot = context - self.low
        out, left = np.full(len(word), -1), np.arange(len(word))
        outside = (slot < 0) | (slot >= self.slots)
        if outside.any():
            at = _find(self.others, context[outside])
            slot[outside] = np.where(at >= 0, at + self.slots, -1)
            left = np.flatnonzero(slot >= 0)
        low, high, word = self._starts(slot[left]), self._starts(slot[left] + 1), word[left]
        open_ = np.flatnonzero(low < high)
        while len(open_):
            if len(open_) < len(left):
                left, low, high, word = (x.take(open_) for x in (left, low, high, word))
            middle = low + high >> 1
            there = self.words(middle)
            hit, less = there == word, there < word
            out[left[hit]] = middle[hit]
            low, high = np.where(less, middle + 1, low), np.where(less, high, middle)
            open_ = np.flatnonzero((low < high) & ~hit)
        return out


def _by_part(part: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """Each part from 0 on, and where it stands."""
    if len(part):
        order = np.argsort(part.astype(np.int16) if part.max() < 1 << 15 else part, kind="stable")
        own, starts = np.unique(part[order], return_index=True)
        yield from ((int(k), o) for k, o in zip(own, np.split(order, starts[1:]), strict=True) if k >= 0)


@dataclass
class Counts:
    """Numbers by place, in files of RANGE_WORDS places; 0 where there is no file, and at -1."""

    paths: list[str | None]

    def at(self, place: np.ndarray) -> np.ndarray:
        out = np.zeros(len(place), np.int64)
        for k, own in _by_part(place // RANGE_WORDS):
            if self.paths[k]:
                out[own] = _values_at(self.paths[k], place[own] - k * RANGE_WORDS)
        return out


@dataclass
class Level:
    """All distinct runs of some number of words, as (context, word): a context is the number of the run
    before the word in the level below, or of a word, and the number after the last is the start of a text.

    A run's own number is its place. Its value is its count in the highest level, and the number of different
    words before it in others. ``hot`` has the figures of the contexts that are spread, each in a column.
    """

    contexts: int
    buckets: int
    spread: np.ndarray
    wide: bool
    paths: list[str | None]
    first: list[int]
    size: int
    links: list[str | None] | None
    values: list[str | None]
    figures: list[str | None]
    hot: np.ndarray
    discounts: tuple[float, float, float]

    def runs(self, k: int) -> Runs:
        return Runs(self.paths[k], bucket_range(k, self.buckets, self.contexts)[0])

    @cached_property
    def _weights(self) -> np.ndarray:
        code = np.arange(1 << 16)
        return _left(np.stack([code >> b & 15 for b in (0, 4, 8, 12)]), self.discounts)

    def look(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Number of each run, -1 if unknown."""
        return self.look_up(context, word, False)[0]

    def look_up(self, context: np.ndarray, word: np.ndarray, full: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Number and value of each run, what follows its context in all, and the weight that the context leaves to the order below."""
        number, value = np.full(len(word), -1, np.int64), np.zeros(len(word))
        after, left = np.zeros(len(word), np.int64), np.ones(len(word))
        known = np.flatnonzero(context >= 0)
        for k, own in _by_part(pair_bucket(context[known], word[known], self.buckets, self.contexts, self.spread)):
            own = known[own]
            here = context[own]
            if self.paths[k]:
                at = self.runs(k).find(here, word[own])
                found = np.flatnonzero(at >= 0)
                at, to = at[found], own[found]
                number[to] = at + self.first[k]
                if full and self.values[k]:
                    value[to] = _values_at(self.values[k], at)
            if full and self.figures[k]:
                low, slots = bucket_range(k, self.buckets, self.contexts)
                inside = np.flatnonzero((here >= low) & (here < low + slots))
                after[own[inside]], left[own[inside]] = _figures_at(self.figures[k], here[inside] - low, self.discounts, self._weights)
        if full:
            at = _find(self.hot[0], context)
            hot = np.flatnonzero(at >= 0)
            after[hot], left[hot] = self.hot[1, at[hot]], _left(self.hot[1:, at[hot]], self.discounts)
        return number, value, after, left

    def suffix(self, number: np.ndarray, start: int) -> np.ndarray:
        """Each run without its first word: its number in the level below, or of a word; ``start`` for the start of a text."""
        out, inner = np.full(len(number), start, np.int64), np.flatnonzero(number < self.size)
        for k, own in _by_part(np.searchsorted(self.first, number[inner], side="right") - 1):
            own = inner[own]
            at = number[own] - self.first[k]
            out[own] = _columns(self.links[k], "<u8")[0][at].astype(np.int64) if self.links else self.runs(k).words(at)
        return out


def walk(vocabulary: Vocabulary, levels: list[Level], windows, full: bool = True) -> Iterator[tuple]:
    """Text, number and count of every token, the number of its longest context, and from all levels values and what follows the contexts."""
    carried = [-1] * len(levels)
    for token, doc, before in windows:
        number, count, context = vocabulary.of_window(token, before)
        begins, looked = before == START, []
        for k, level in enumerate(levels):
            own, *figures = level.look_up(context, number, full)
            context = np.concatenate([[carried[k]], own[:-1]])
            context[begins] = level.size
            carried[k] = own[-1]
            looked.append(figures)
        yield doc, number, count, context, looked


@dataclass
class Model:
    vocabulary: Vocabulary
    levels: list[Level]
    before: Counts
    lower: tuple[float, float, float]
    distinct_pairs: int
    rest: float

    @property
    def wide(self) -> bool:
        return self.levels[0].wide

    def log10(self, number: np.ndarray, looked: list[list[np.ndarray]]) -> np.ndarray:
        """Base-10 logarithm of the probability of every token after those before it."""
        before = self.before.at(number)
        p = np.maximum(before - _discount(before, self.lower), 0) / max(1, self.distinct_pairs) + self.rest / (self.vocabulary.size + 1)
        for level, (value, after, left) in zip(self.levels, looked, strict=True):
            p = np.where(after > 0, np.maximum(value - _discount(value, level.discounts), 0) / np.maximum(after, 1) + left * p, p)
        return np.log10(p)


def _key(first: np.ndarray, second: np.ndarray, wide: bool = False) -> np.ndarray:
    """One sortable key of two numbers: 64 bits, or 16 bytes where numbers need more than 32 bits."""
    if not wide:
        return first.astype(np.uint64) << np.uint64(32) | second.astype(np.uint64)
    return np.stack([first, second], axis=1).astype(">u8").view("S16").ravel()


def _halves(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if key.dtype.kind == "S":
        both = np.ascontiguousarray(key).view(">u8").reshape(-1, 2).astype(np.int64)
        return both[:, 0], both[:, 1]
    return (key >> np.uint64(32)).astype(np.int64), (key & np.uint64(2**32 - 1)).astype(np.int64)


def pair_bucket(first: np.ndarray, second: np.ndarray, buckets: int, contexts: int, spread: np.ndarray) -> np.ndarray:
    by_range = first * buckets // (contexts + 1)
    hot = np.flatnonzero(_find(spread, first) >= 0)
    by_range[hot] = (textkit.mix64(first[hot].astype(np.uint64) * _SPREAD + second[hot].astype(np.uint64)) % np.uint64(buckets)).astype(np.int64)
    return by_range


def bucket_range(k: int, buckets: int, contexts: int) -> tuple[int, int]:
    """The first context of a bucket, and how many it has."""
    low, high = (-(-i * (contexts + 1) // buckets) for i in (k, k + 1))
    return low, high - low


def _discount(count: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    return np.array([0.0, *d])[np.minimum(count, 3).astype(np.int8)]


def _discounts(n: list[int]) -> tuple[float, float, float]:
    """The three discounts from how many entries have counts 1 to 4; fixed ones if some count has none."""
    if min(n) <= 0:
        return 0.5, 0.75, 0.9
    y = n[0] / (n[0] + 2 * n[1])
    raw = [k + 1 - (k + 2) * y * n[k + 1] / n[k] for k in range(3)]
    return tuple(min(max(d, 0.05), k + 0.95) for k, d in enumerate(raw))


def count_words(train: DataFrame, folder: str) -> tuple[Vocabulary, DataFrame]:
    """The vocabulary, and the stored table of hashes and counts that it was made of."""

    def run(batches):
        for key, count in _gathered(token for token, _, _ in _all_windows(batches)):
            yield pa.record_batch([pa.array(key.view(np.int64)), pa.array(count)], ["h", "c"])

    rows = durable(train.select("text").mapInArrow(run, "h bigint, c bigint").groupBy("h").agg(F.sum("c").alias("c")), "words")
    size, tokens = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum("c"), F.lit(0))).head()
    bits = max(0, (max(1, size // RANGE_WORDS + (size > RANGE_WORDS)) - 1).bit_length())

    def write(table: pa.Table) -> pa.Table:
        h, c = table.column("h").to_numpy().view(np.uint64), table.column("c").to_numpy()
        order = np.argsort(h)
        path = _write_counted(folder, "vocabulary", h[order], c[order])
        return pa.table({"part": table.column("part")[:1], "path": [path], "n": pa.array([len(h)], pa.int64())})

    part = F.shiftrightunsigned("h", 64 - bits).cast("int") if bits else F.lit(0)
    files = rows.withColumn("part", part).groupBy("part").applyInArrow(write, "part int, path string, n bigint")
    paths, sizes = [None] * (1 << bits), [0] * (1 << bits)
    for r in files.collect():
        paths[r["part"]], sizes[r["part"]] = r["path"], r["n"]
    return Vocabulary(bits, paths, [int(x) for x in np.cumsum([0, *sizes[:-1]])], size, int(tokens)), rows


def _hot_words(vocabulary: Vocabulary, rows: DataFrame, buckets: int) -> np.ndarray:
    """Numbers of words with over an eighth of a bucket's share: fewer than 8 * buckets by their definition."""
    hot = rows.where(F.col("c") > vocabulary.tokens / buckets / 8).select("h").toPandas()["h"].to_numpy(np.int64)
    # the start of a text is the first word of as many pairs as there are texts
    return np.append(np.sort(vocabulary.numbers(np.sort(hot.view(np.uint64)))[0]), vocabulary.size)


def _sums(context: np.ndarray, value: np.ndarray) -> list[np.ndarray]:
    """Contexts, sums of their values, and how many values are 1, 2 and more; the values of a context stand together."""
    new = np.flatnonzero(np.concatenate([[True], context[1:] != context[:-1]])) if len(context) else np.empty(0, np.int64)
    return [context[new], *(np.add.reduceat(x, new).astype(np.int64) if len(new) else new for x in (value, value == 1, value == 2, value > 2))]


#: Rows that a bucket gives out: sums of a spread context, words before runs of a file of the level below, its files, and frequent runs.
_CONTEXT, _BEFORE, _FILE, _HOT = range(4)
_ROW = "kind int, a bigint, n bigint, n1 bigint, n2 bigint, n3 bigint, bucket int, path string, link string, value string, figure string, run binary"


def _rows(*parts: list[dict]) -> pa.Table:
    kinds = {"int": pa.int32(), "bigint": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    return pa.Table.from_pylist([r for p in parts for r in p], pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in _ROW.split(", ")]))


def _tally(value: np.ndarray) -> dict:
    """How many values there are, and how many are 1 to 4."""
    return dict(zip(("n", "n1", "n2", "n3"), np.bincount(np.minimum(value, 5).astype(np.int64), minlength=6)[1:5].tolist(), strict=True))


def _figures(folder: str, low: int, slots: int, spread: np.ndarray, context: np.ndarray, value: np.ndarray) -> tuple[str, list[dict]]:
    """The file of the contexts of a bucket, and rows for those that are spread."""
    each, *sums = _sums(context, value)
    hot = _find(spread, each) >= 0
    path = _write_figures(folder, slots, each[~hot] - low, [x[~hot] for x in sums])
    return path, [{"kind": _CONTEXT, "a": a, "n": n, "n1": n1, "n2": n2, "n3": n3} for a, n, n1, n2, n3 in np.stack([each, *sums])[:, hot].T.tolist()]


def _hot_figures(found: DataFrame) -> np.ndarray:
    """Of the spread contexts, of which there are fewer than 8 * buckets and one."""
    sums = found.where(f"kind = {_CONTEXT}").groupBy("a").agg(*[F.sum(c).alias(c) for c in ("n", "n1", "n2", "n3")]).collect()
    return np.array(sorted(map(tuple, sums)), np.int64).reshape(-1, 5).T


def _dealt(target: np.ndarray, first: np.ndarray) -> list[dict]:
    """How often each number occurs, packed for each file that begins at the numbers ``first``."""
    key, n = np.unique(target, return_counts=True)
    part = np.searchsorted(first, key, side="right") - 1
    own, starts = np.unique(part, return_index=True)
    return [{"kind": _BEFORE, "a": int(k), "run": _packed(x.astype(np.uint64), c)} for k, x, c in zip(own, np.split(key, starts[1:]), np.split(n, starts[1:]), strict=True) if len(x)]


def _summed(table: pa.Table, size: int, first: int) -> np.ndarray:
    """Sums of the packed counts of a file of so many places."""
    out = np.zeros(size, np.int64)
    for run in table.column("run"):
        key, n = _unpacked(run.as_py())
        out[key.astype(np.int64) - first] += n
    return out


def train_model(train: DataFrame, bucket_tokens: int = BUCKET_TOKENS, narrow_words: int = NARROW_WORDS, order: int = ORDER) -> Model:
    """Count all of ``train`` and return the model: paths and a few figures. Beyond ``narrow_words`` words or contexts, keys are wide."""
    if order < 2:
        raise ValueError("the least order is 2")
    spark = train.sparkSession
    folder = scratch_path(spark, "ngrams")
    store, place = fs.FileSystem.from_uri(folder)
    store.create_dir(place, recursive=True)
    with scratch_scope(own := f"ngrams-{uuid.uuid4().hex[:12]}"):
        vocabulary, rows = count_words(train, folder)
        buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-vocabulary.tokens // bucket_tokens))
        spread, contexts = _hot_words(vocabulary, rows, buckets), vocabulary.size
    del rows
    _release(spark, own)
    levels: list[Level] = []
    for k in range(2, order + 1):
        with scratch_scope(own):
            level, found = _count_level(train, vocabulary, levels, k == order, contexts, spread, buckets, max(contexts, vocabulary.size) > narrow_words, folder)
            _release(spark)
            before = found.where(f"kind = {_BEFORE}").select("a", "run")
            if levels:
                _continue_level(levels[-1], before, folder)
            else:
                words, lower, rest = _words_before(vocabulary, before, level.size, folder)
            if k == order:
                level.hot = _hot_figures(found)
            hot = [level.first[r["bucket"]] + r["a"] for r in found.where(f"kind = {_HOT}").select("bucket", "a").collect()]
        del found, before
        _release(spark, own)
        spread, contexts = np.array([*sorted(hot), level.size], np.int64), level.size
        levels.append(level)
    return Model(vocabulary, levels, words, lower, levels[0].size, rest)


def _release(spark, scope: str | None = None) -> None:
    """Delete the tables of a scope, and collect garbage, as only then do the shuffles of ended jobs go."""
    if scope:
        release_scratch(spark, scope)
    gc.collect()
    spark._jvm.System.gc()


def _count_level(train: DataFrame, vocabulary: Vocabulary, below: list[Level], top: bool, contexts: int, spread: np.ndarray, buckets: int, wide: bool, folder: str) -> tuple[Level, DataFrame]:
    """Count the runs of one word more than the levels ``below`` have; what the buckets give out is stored."""
    frequent = vocabulary.tokens / buckets / 8

    def keys(batches) -> Iterator[np.ndarray]:
        for _, number, _, context, _ in walk(vocabulary, below, _all_windows(batches), False):
            yield _key(context, number, wide)

    def count(batches):
        for key, n in _gathered(keys(batches)):
            own, runs = [], []
            for k, o in _by_part(pair_bucket(*_halves(key), buckets, contexts, spread)):
                own.append(k)
                runs.append(_packed(key[o], n[o]))
            yield pa.record_batch([pa.array(own, pa.int32()), pa.array(runs, pa.binary())], ["bucket", "run"])

    def merge(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        low, slots = bucket_range(bucket, buckets, contexts)
        runs = [_unpacked(r) for r in table.column("run").to_pylist()]
        key, n = _merge([x for x, _ in runs], [c for _, c in runs])
        del runs
        context, word = _halves(key)
        del key
        context, word, n = _range_first(context, low, slots, word, n)
        row = {"kind": _FILE, "bucket": bucket, "a": len(n), "path": _write_runs(folder, f"level{len(below) + 2}", low, slots, context, word)}
        hot = [] if top else [{"kind": _HOT, "bucket": bucket, "a": a} for a in np.flatnonzero(n > frequent).tolist()]
        spread_rows = []
        if top:
            row |= _tally(n) | {"value": _write_values(folder, "counts", n)}
            row["figure"], spread_rows = _figures(folder, low, slots, spread, context, n)
        if below:
            # the run without its first word, in the level below
            start = below[-2].size if len(below) > 1 else vocabulary.size
            target = below[-1].look(below[-1].suffix(context, start), word)
            first = np.array(below[-1].first)
            if not top:
                row["link"] = _write(folder, "links", target.astype("<u8"))
        else:
            target, first = word, np.arange(0, vocabulary.size + 1, RANGE_WORDS)
        out = _rows([row], hot, spread_rows, _dealt(target, first))
        textkit.trim()
        return out

    runs = train.select("text").mapInArrow(count, "bucket int, run binary")
    found = durable(runs.groupBy("bucket").applyInArrow(merge, _ROW), "sums")
    paths: list[str | None] = [None] * buckets
    links, values, figures, sizes, tally = list(paths), list(paths), list(paths), [0] * buckets, np.zeros(4, np.int64)
    for r in found.where(f"kind = {_FILE}").drop("run").collect():
        k = r["bucket"]
        paths[k], links[k], values[k], figures[k], sizes[k] = r["path"], r["link"], r["value"], r["figure"], r["a"]
        tally += [r[c] or 0 for c in ("n", "n1", "n2", "n3")]
    first = [int(x) for x in np.cumsum([0, *sizes[:-1]])]
    hot = np.empty((5, 0), np.int64)
    return Level(contexts, buckets, spread, wide, paths, first, sum(sizes), links if below and not top else None, values, figures, hot, _discounts(tally.tolist())), found


def _words_before(vocabulary: Vocabulary, before: DataFrame, pairs: int, folder: str) -> tuple[Counts, tuple[float, float, float], float]:
    """How many different words come before each word, the discounts of that, and what is left for all words."""
    size = vocabulary.size

    def write(table: pa.Table) -> pa.Table:
        part = table.column("a")[0].as_py()
        value = _summed(table, min(RANGE_WORDS, size - part * RANGE_WORDS), part * RANGE_WORDS)
        return _rows([{"kind": _FILE, "bucket": part, "a": int(np.count_nonzero(value)), "path": _write_values(folder, "before", value)} | _tally(value)])

    paths: list[str | None] = [None] * (size // RANGE_WORDS + 1)
    tally, more = np.zeros(4, np.int64), 0
    for r in before.groupBy("a").applyInArrow(write, _ROW).collect():
        paths[r["bucket"]] = r["path"]
        tally += [r[c] for c in ("n", "n1", "n2", "n3")]
        more += r["a"] - r["n"] - r["n1"]
    d = _discounts(tally.tolist())
    return Counts(paths), d, (d[0] * int(tally[0]) + d[1] * int(tally[1]) + d[2] * more) / pairs if pairs else 1.0


def _continue_level(level: Level, before: DataFrame, folder: str) -> None:
    """Give a level that is not the highest its values: how many different words come before each run."""

    def write(table: pa.Table) -> pa.Table:
        k = table.column("a")[0].as_py()
        low, slots = bucket_range(k, level.buckets, level.contexts)
        context = level.runs(k).contexts()
        value = _summed(table, len(context), level.first[k])
        path, spread_rows = _figures(folder, low, slots, level.spread, context, value)
        out = _rows([{"kind": _FILE, "bucket": k, "value": _write_values(folder, "continued", value), "figure": path} | _tally(value)], spread_rows)
        textkit.trim()
        return out

    found = durable(before.groupBy("a").applyInArrow(write, _ROW), "continued")
    tally = np.zeros(4, np.int64)
    for r in found.where(f"kind = {_FILE}").collect():
        level.values[r["bucket"]], level.figures[r["bucket"]] = r["value"], r["figure"]
        tally += [r[c] for c in ("n", "n1", "n2", "n3")]
    level.discounts, level.hot = _discounts(tally.tolist()), _hot_figures(found)


def _packed(key: np.ndarray, count: np.ndarray) -> bytes:
    """A sorted run as compressed byte planes of its keys, of their differences if they are numbers, and counts."""
    raw = key if key.dtype.kind == "S" else np.diff(key, prepend=np.uint64(0)).astype("<u8")
    planes = np.ascontiguousarray(np.ascontiguousarray(raw).view(np.uint8).reshape(len(key), -1).T)
    body = planes.tobytes() + count.astype("<u8").view(np.uint8).reshape(len(key), 8).T.tobytes()
    return struct.pack("<QB", len(key), raw.dtype.itemsize) + pa.compress(body, codec="zstd", asbytes=True)


def _unpacked(run: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, width = struct.unpack_from("<QB", run)
    body = np.frombuffer(pa.decompress(memoryview(run)[9:], (width + 8) * n, codec="zstd", asbytes=True), np.uint8)
    raw = np.ascontiguousarray(body[: width * n].reshape(width, n).T)
    key = np.cumsum(raw.view("<u8").ravel()) if width == 8 else raw.view("S16").ravel()
    return key, np.ascontiguousarray(body[width * n :].reshape(8, n).T).view("<u8").ravel().astype(np.int64)


def score_texts(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, n_tokens, n_known, base_score and score of each row of ``docs``."""

    def run(batches):
        for batch in batches:
            for part in textkit.slices(batch, "text", SLICE_BYTES):
                n = len(part)
                n_tokens, n_known, base, score = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n), np.zeros(n)
                for doc, number, count, _, looked in walk(model.vocabulary, model.levels, token_windows(part.column(1))):
                    low = int(doc[0])
                    here = slice(low, int(doc[-1]) + 1)
                    add = lambda x: np.bincount(doc - low, x)  # noqa: E731, B023
                    n_tokens[here] += add(np.ones(len(doc))).astype(np.int64)
                    n_known[here] += add(count > 0).astype(np.int64)
                    base[here] += add(np.log10((count + 1) / (model.vocabulary.tokens + model.vocabulary.size + 1)))
                    score[here] += add(model.log10(number, looked))
                yield pa.record_batch([part.column(0), *map(pa.array, (n_tokens, n_known, base, score))], ["doc_id", "n_tokens", "n_known", "base_score", "score"])

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(run, "doc_id bigint, n_tokens bigint, n_known bigint, base_score double, score double")


def score_documents(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """Scores of all documents by a model of those outside the held-out fold."""
    rows = docs.select("doc_id", text_or_empty().alias("text"))
    model = train_model(rows.where(fold_of("doc_id", 7) != 2), order=order)
    scored = score_texts(rows, model)
    return scored.select("doc_id", (fold_of("doc_id", 7) == 2).alias("held_out"), "n_tokens", "n_known", F.lit(model.vocabulary.tokens).cast("bigint").alias("train_tokens"), "base_score", "score")
