"""Array work on many texts at once, inside Python workers.

A batch of texts is one byte buffer with offsets; words, their hashes and their documents are
arrays over that buffer. No text is handled by a Python loop over its characters or words.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; a longer text is a slice of its own.
SLICE_BYTES = 8 << 20
#: Bytes whose words are hashed at once: the arrays for it are some fifty times as large.
WINDOW_BYTES = 512 << 10

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def trim() -> None:
    """Give freed memory back to the machine: workers live on, beside the executor's heap."""
    pa.default_memory_pool().release_unused()
    release = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if release:
        release(0)


def slices(batch: pa.RecordBatch, text: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows with at most ``limit`` bytes of text, or one row."""
    size = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends = np.cumsum(size)
    start = 0
    while start < len(size):
        base = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, base + limit, side="right")))
        yield batch.slice(start, stop - start)
        start = stop
    trim()


def flat_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts together, and where each begins (one more for the end). Null is empty."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    buf = np.frombuffer(data, dtype=np.uint8) if data else np.empty(0, np.uint8)
    first = int(offsets[0]) if len(offsets) else 0
    return buf[first : int(offsets[-1])], (offsets - first).astype(np.int64)


def windows(column: pa.Array, limit: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Runs of at most ``limit`` bytes, or one word: the first text, the bytes, and where the texts begin among them.

    Runs end before white space or a text, so that words stay whole; a long text lies in many runs,
    and what is kept of a run does not grow with the text. Texts without bytes may be in any run, or none.
    """
    whole, offsets = flat_bytes(column)
    low = 0
    while low < len(whole):
        high, size = min(len(whole), low + limit), limit
        while high < len(whole):
            begin = offsets[np.searchsorted(offsets, high, side="right") - 1]
            blank = np.flatnonzero(_SPACE[whole[max(low + 1, high - 4096) : high + 1]])
            if begin > low or len(blank):
                high = max(int(begin), max(low + 1, high - 4096) + int(blank[-1]) if len(blank) else 0)
                break
            # no end in sight: look further back, then on
            blank = np.flatnonzero(_SPACE[whole[low + 1 : high]])
            if len(blank):
                high = low + 1 + int(blank[-1])
                break
            size *= 2
            high = min(len(whole), low + size)
        first = int(np.searchsorted(offsets, low, side="right")) - 1
        last = int(np.searchsorted(offsets, high, side="left"))
        yield first, whole[low:high], np.clip(offsets[first : last + 1] - low, 0, high - low)
        low = high


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers (the finaliser of a public generator)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin, end and document of every run of bytes that are not white space."""
    if not len(buf):
        none = np.empty(0, np.int64)
        return none, none, none
    solid = ~_SPACE[buf]
    edge = np.empty(len(buf), bool)
    edge[0] = True
    edge[1:] = ~solid[:-1]
    cuts = offsets[:-1][offsets[:-1] < len(buf)]
    edge[cuts] = True
    begin = np.flatnonzero(solid & edge)
    last = np.empty(len(buf), bool)
    last[-1] = True
    last[:-1] = ~solid[1:]
    cuts = offsets[1:][offsets[1:] > 0] - 1
    last[cuts] = True
    end = np.flatnonzero(solid & last) + 1
    return begin, end, np.searchsorted(offsets, begin, side="right") - 1


_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(16, (n - 1).bit_length())
    if size not in _powers:
        _powers.clear()
        base = int(_MULTIPLIER) | 1
        inverse = pow(base, -1, 1 << 64)
        tables = []
        for b in (base, inverse):
            t = np.full(size + 1, np.uint64(b))
            t[0] = 1
            tables.append(np.multiply.accumulate(t))
        _powers[size] = (tables[0], tables[1])
    return _powers[size]


def span_hashes(buf: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hash of each byte span, from running sums of byte * base^place (mod 2^64)."""
    if not len(begin):
        return np.empty(0, np.uint64)
    up, down = _power_tables(len(buf))
    sums = np.empty(len(buf) + 1, np.uint64)
    sums[0] = 0
    scattered = mix64(np.arange(1, 257, dtype=np.uint64) * _MULTIPLIER)[buf]
    np.cumsum(scattered * up[: len(buf)], out=sums[1:])
    value = (sums[end] - sums[begin]) * down[begin]
    return mix64(value + (end - begin).astype(np.uint64) * _MULTIPLIER)


def ragged_take(flat: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The concatenation of flat[start_i : start_i + length_i]."""
    total = int(length.sum())
    shift = np.cumsum(length) - length
    return flat[np.repeat(start - shift, length) + np.arange(total)]
