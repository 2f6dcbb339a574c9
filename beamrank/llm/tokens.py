"""Token ids of whole texts by the ``tokenizers`` library, each distinct piece encoded once.

A text is cut only where both vocabularies always end a piece: before white space that follows a
visible character, after a single line end or tab between visible ones, between ASCII letters,
digits and punctuation (the apostrophe apart), and around special tokens, which the library takes
out first. Ids of a text are then the ids of its pieces in order. Texts are worked on in windows
that end at such a cut, so that one very long text needs no more memory than its ids; only a run
without any cut goes to the library whole.

Distinct pieces of a window are found by Arrow's dictionary encoding and looked up, all at once, in
sorted arrays of the hashes of pieces met before; a hit counts only if the bytes are equal. Only
new pieces are handled one by one: one plain word goes straight to the library's merge model, any
other piece to its whole encoder. When the arrays are full, pieces that were not met since the last
time are given up.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa

from beamrank.llm import textkit

#: Distinct pieces a worker keeps, about 50 bytes each.
CACHE_PIECES = 600_000

#: Bytes of text encoded at once.
SLICE_BYTES = 2 << 20

#: 0 stands for bytes beside which no text is cut by the table.
_LETTER, _DIGIT, _SIGN, _BLANK, _QUOTE = 1, 2, 3, 4, 5


def _kinds() -> np.ndarray:
    kind = np.zeros(256, np.uint8)
    for code in range(33, 127):
        c = chr(code)
        kind[code] = _LETTER if c.isalpha() else _DIGIT if c.isdigit() else _SIGN
    kind[ord("'")] = _QUOTE
    kind[[9, 10, 11, 12, 13, 32]] = _BLANK
    return kind


def _cuts() -> np.ndarray:
    """Whether a text is cut between a byte of one kind and one of another, at 8 * first + second."""
    cut = np.zeros((8, 8), np.uint8)
    plain = (_LETTER, _DIGIT, _SIGN)
    for a in plain:
        for b in plain:
            cut[a, b] = a != b
    cut[[*plain, _QUOTE], _BLANK] = 1
    return cut.ravel()


_KIND, _CUT = _kinds(), _cuts()
_KIND_TABLE, _CUT_TABLE = _KIND.tobytes(), _CUT.tobytes() + bytes(192)


def _after_visible(buf: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Which of the places ``at`` follow a character beyond ASCII that is no white space.

    All white space beyond ASCII begins with the bytes C2, E1, E2 or E3 80.
    """
    back = lambda k: np.where(at >= k, buf[np.maximum(at - k, 0)], 0)
    one, two, three, four = (back(k) for k in (1, 2, 3, 4))
    tail = (one & 0xC0) == 0x80
    short = (two >= 0xC3) & (two <= 0xDF)
    middle = ((two & 0xC0) == 0x80) & ((three == 0xE0) | ((three >= 0xE4) & (three <= 0xEF)) | ((three == 0xE3) & (two > 0x80)))
    long = ((two & 0xC0) == 0x80) & ((three & 0xC0) == 0x80) & (four >= 0xF0)
    return tail & (short | middle | long)


def _byte_letters() -> dict[int, str]:
    """The printable stand-in that byte-level vocabularies use for each byte, from their rule."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in own}
    for b in range(256):
        if b not in table:
            table[b] = chr(256 + len(table) - len(own))
    return table


_STAND_IN = _byte_letters()


class PieceStore:
    """Pieces by hash in sorted arrays, with their bytes and ids. Look-ups compare bytes."""

    def __init__(self, limit: int):
        self.limit = limit
        self.hash = np.empty(0, np.uint64)
        self.met = np.empty(0, bool)
        self.text_at = self.ids_at = np.empty(0, np.int64)
        self.text_n = self.ids_n = np.empty(0, np.int32)
        self.text, self.ids = np.empty(0, np.uint8), np.empty(0, np.uint32)

    def find(self, hashes: np.ndarray, buf: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Place of each piece, -1 if it is not held."""
        if not len(self.hash):
            return np.full(len(hashes), -1)
        order = np.argsort(hashes)
        place = np.empty(len(hashes), np.int64)
        place[order] = np.minimum(np.searchsorted(self.hash, hashes[order]), len(self.hash) - 1)
        hit = np.flatnonzero((self.hash[place] == hashes) & (self.text_n[place] == n))
        size = n[hit].astype(np.int64)
        same = textkit.ragged_take(buf, at[hit], size) == textkit.ragged_take(self.text, self.text_at[place[hit]], size)
        differs = np.add.reduceat(~same, np.cumsum(size) - size) if len(hit) else np.empty(0, np.int64)
        hit = hit[differs == 0]
        out = np.full(len(hashes), -1)
        out[hit] = place[hit]
        self.met[out[hit]] = True
        return out

    def add(self, hashes: np.ndarray, buf: np.ndarray, at: np.ndarray, n: np.ndarray, ids: np.ndarray, ids_n: np.ndarray) -> None:
        """Take in pieces that are not held; of equal hashes one stays."""
        if len(self.hash) + len(hashes) > self.limit:
            self._keep(np.flatnonzero(self.met))
            self.met[:] = False
        _, first = np.unique(hashes, return_index=True)
        first = first[: max(0, self.limit - len(self.hash))]
        place = np.searchsorted(self.hash, hashes[first])
        clash = self.hash[np.minimum(place, len(self.hash) - 1)] == hashes[first] if len(self.hash) else np.zeros(len(first), bool)
        first, place = first[~clash], place[~clash]
        starts = np.cumsum(ids_n) - ids_n
        put = lambda old, new: np.insert(old, place, new)
        self.hash, self.met = put(self.hash, hashes[first]), put(self.met, False)
        self.text_at = put(self.text_at, len(self.text) + np.cumsum(n[first]) - n[first])
        self.ids_at = put(self.ids_at, len(self.ids) + np.cumsum(ids_n[first]) - ids_n[first])
        self.text_n, self.ids_n = put(self.text_n, n[first]), put(self.ids_n, ids_n[first])
        self.text = np.concatenate([self.text, textkit.ragged_take(buf, at[first], n[first])])
        self.ids = np.concatenate([self.ids, textkit.ragged_take(ids, starts[first], ids_n[first])])

    def _keep(self, rows: np.ndarray) -> None:
        self.text = textkit.ragged_take(self.text, self.text_at[rows], self.text_n[rows])
        self.ids = textkit.ragged_take(self.ids, self.ids_at[rows], self.ids_n[rows])
        self.hash, self.met, self.text_n, self.ids_n = self.hash[rows], self.met[rows], self.text_n[rows], self.ids_n[rows]
        self.text_at = np.cumsum(self.text_n, dtype=np.int64) - self.text_n
        self.ids_at = np.cumsum(self.ids_n, dtype=np.int64) - self.ids_n


class PieceEncoder:
    """Ids of batches of texts. ``fold``: the vocabulary lower-cases and drops white space."""

    def __init__(self, path: str, cache_pieces: int = CACHE_PIECES, window: int = SLICE_BYTES):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.fold = self.tokenizer.normalizer is not None
        self.store, self.window = PieceStore(cache_pieces), window
        self.special = sorted((t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()), key=len, reverse=True)
        self.special_size = max(map(len, self.special), default=0)

    def piece(self, key: bytes) -> list[int]:
        text = key.decode("utf-8", "replace")
        word = text[1:] if text[:1] == " " else text
        if word.isalpha() and max(word) < "Ā":
            if self.fold:
                key = word.lower().encode()
            return [t.id for t in self.model.tokenize(key.decode("latin-1").translate(_STAND_IN))]
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _specials(self, raw: bytes) -> list[tuple[int, int]]:
        """Where special tokens stand."""
        there = [t for t in self.special if t in raw]
        return [m.span() for m in re.finditer(b"|".join(map(re.escape, there)), raw)] if there else []

    def _cut(self, raw: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """Places where pieces begin; ``begins`` are the beginnings of texts."""
        kind = np.frombuffer(raw.tobytes().translate(_KIND_TABLE), np.uint8)
        joint = kind[:-1] << 3
        joint |= kind[1:]
        cut = np.zeros(len(raw), bool)
        cut[1:] = np.frombuffer(joint.tobytes().translate(_CUT_TABLE), bool)
        blank = np.flatnonzero(joint == _BLANK) + 1
        cut[blank[_after_visible(raw, blank)]] = True
        # a single line end or tab between visible characters is a piece of its own
        after = np.flatnonzero((kind[1:-1] == _BLANK) & (raw[1:-1] != 32) & cut[1:-1] & (kind[2:] >= _LETTER) & (kind[2:] <= _SIGN)) + 2
        cut[after] = True
        cut[begins[begins < len(raw)]] = True
        cut[:1] = True
        for a, b in self._specials(raw.tobytes()):
            # not one that lies across two texts
            if np.searchsorted(begins, a, side="right") == np.searchsorted(begins, b):
                cut[a:b] = False
                cut[a] = True
                cut[b : b + 1] = True
        return np.flatnonzero(cut)

    def _pieces(self, buf: np.ndarray, begin: np.ndarray, stop: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces that begin at ``begin``, and how many each has."""
        ends = np.append(begin, stop).astype(np.int32)
        found = pa.Array.from_buffers(pa.binary(), len(begin), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(buf))]).dictionary_encode()
        text, offsets = textkit.flat_bytes(found.dictionary)
        at, n = offsets[:-1], np.diff(offsets)
        hashes = textkit.span_hashes(text, at, offsets[1:])
        place = self.store.find(hashes, text, at, n)
        new, raw = np.flatnonzero(place < 0), text.tobytes()
        fresh: list[int] = []
        sizes = np.empty(len(new), np.int64)
        for i, (a, b) in enumerate(zip(at[new].tolist(), offsets[1:][new].tolist(), strict=True)):
            ids = self.piece(raw[a:b])
            fresh += ids
            sizes[i] = len(ids)
        own = np.array(fresh, np.uint32)
        start, count = np.empty(len(at), np.int64), np.empty(len(at), np.int64)
        known = place >= 0
        start[known], count[known] = self.store.ids_at[place[known]], self.store.ids_n[place[known]]
        start[new], count[new] = len(self.store.ids) + np.cumsum(sizes) - sizes, sizes
        index = found.indices.to_numpy()
        length = count[index]
        ids = textkit.ragged_take(np.concatenate([self.store.ids, own]), start[index], length)
        self.store.add(hashes[new], text, at[new], n[new], own, sizes)
        return ids, length

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids together, and where those of each text begin (one more for the end)."""
        whole, offsets = textkit.flat_bytes(column)
        parts, bounds = [np.empty(0, np.uint32)], np.zeros(len(offsets), np.int64)
        low, done = 0, 0
        while low < len(whole):
            size = self.window
            while True:
                high = min(len(whole), low + size)
                # what lies ahead settles the cuts before it
                seen = whole[low : min(len(whole), high + self.special_size)]
                begins = offsets[np.searchsorted(offsets, low) : np.searchsorted(offsets, low + len(seen))] - low
                begin = self._cut(seen, begins)
                stop = len(whole) - low if high == len(whole) else begin[max(0, np.searchsorted(begin, high - low, side="right") - 1)]
                if stop:
                    break
                size *= 2
            begin = begin[begin < stop]
            buf = textkit.LOWER[seen[:stop]] if self.fold else seen[:stop]
            if self.fold:
                for a, b in self._specials(seen[:stop].tobytes()):
                    buf[a:b] = seen[a:b]
            ids, length = self._pieces(buf, begin, int(stop))
            here = slice(np.searchsorted(offsets, low), np.searchsorted(offsets, low + stop))
            sums = np.concatenate([[0], np.cumsum(length)])
            bounds[here] = done + sums[np.searchsorted(begin, offsets[here] - low)]
            parts.append(ids)
            low, done = low + int(stop), done + len(ids)
        bounds[np.searchsorted(offsets, len(whole)) :] = done
        return np.concatenate(parts), bounds


_encoders: dict[str, PieceEncoder] = {}


def encoder(path: str) -> PieceEncoder:
    """The encoder of this worker process for a vocabulary file."""
    if path not in _encoders:
        _encoders[path] = PieceEncoder(path)
    return _encoders[path]


def vocabulary(name: str) -> str:
    """Place of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)
