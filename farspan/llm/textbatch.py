"""Vectorised word and byte arithmetic over the flat UTF-8 buffer of an Arrow text column.

Every kernel treats a null text as an empty one and never lets a word, line or shingle cross
a document boundary.  A chunk holds whole documents up to ``limit`` bytes, or one longer document.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 19
#: Spans beyond this many bytes are hashed by BLAKE2b, one by one; shorter ones eight bytes at a time, all together.
LONG_SPAN = 256

_rng = np.random.default_rng(20240607)
_ODD = _rng.integers(1, 2**63, 4, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MIX_1, _MIX_2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_MASK = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)

IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser: equal inputs stay equal, different ones stay different."""
    x = (x ^ (x >> np.uint64(30))) * _MIX_1
    x = (x ^ (x >> np.uint64(27))) * _MIX_2
    return x ^ (x >> np.uint64(31))


def _absorb(state: np.ndarray, lane: np.ndarray, seed: int) -> np.ndarray:
    """One step of the chain over eight-byte lanes; for a given state it is bijective in the lane."""
    return mix64((state ^ lane) * _ODD[seed])


class TextChunk:
    """``data``: the bytes of all texts end to end; text d is data[off[d]:off[d + 1]]."""

    def __init__(self, data: np.ndarray, off: np.ndarray):
        self.data, self.off = data, off
        self._lanes: dict[bool, np.ndarray] = {}

    @classmethod
    def of(cls, column: pa.Array) -> TextChunk:
        column = pc.fill_null(column, "")
        wide = pa.types.is_large_string(column.type)
        _, offsets, data = column.buffers()
        n = len(column)
        if n == 0 or data is None:
            return cls(np.zeros(0, np.uint8), np.zeros(n + 1, np.int64))
        off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
        return cls(np.frombuffer(data, np.uint8)[off[0] : off[-1]], off - off[0])

    @classmethod
    def of_texts(cls, texts: list[str | None]) -> TextChunk:
        return cls.of(pa.array(texts, pa.large_string()))

    def __len__(self) -> int:
        return len(self.off) - 1

    def lanes(self, lower: bool = False) -> np.ndarray:
        """At each position the eight bytes from there as one little-endian number; zeros follow the text."""
        if lower not in self._lanes:
            padded = np.zeros(len(self.data) + 8, np.uint8)
            padded[:-8] = LOWER[self.data] if lower else self.data
            self._lanes[lower] = np.ndarray(len(self.data) + 1, "<u8", padded, strides=(1,))
        return self._lanes[lower]

    def span_hash(self, start: np.ndarray, end: np.ndarray, lower: bool = False, seed: int = 0) -> np.ndarray:
        """64-bit hashes of data[start:end]; equal bytes give equal hashes wherever they lie, and the hashes of two seeds
        (0 to 2) are independent.  Spans of one length up to eight bytes never share a hash."""
        lanes, size = self.lanes(lower), end - start
        state = mix64(size.astype(np.uint64) * _ODD[3] + _ODD[seed])
        state = _absorb(state, lanes[start] & _MASK[np.minimum(size, 8)], seed)
        more, done = np.flatnonzero((size > 8) & (size <= LONG_SPAN)), 8
        while len(more):
            lane = lanes[start[more] + done] & _MASK[np.minimum(size[more] - done, 8)]
            state[more] = _absorb(state[more], lane, seed)
            done += 8
            more = more[size[more] > done]
        for i in np.flatnonzero(size > LONG_SPAN).tolist():
            own = self.data[start[i] : end[i]]
            digest = hashlib.blake2b((LOWER[own] if lower else own).tobytes(), digest_size=32).digest()
            state[i] = int.from_bytes(digest[8 * seed : 8 * seed + 8], "little")
        return state

    def gram_hash(self, k: int, seed: int = 0) -> np.ndarray:
        """64-bit hashes of the k bytes from every position that has as many."""
        n = len(self.data) - k + 1
        if n <= 0:
            return np.zeros(0, np.uint64)
        lanes, state = self.lanes(), np.full(n, _ODD[seed])
        for at in range(0, k, 8):
            state = _absorb(state, lanes[at : at + n] & _MASK[min(8, k - at)], seed)
        return state

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of all words ``[^\\x20\\x09-\\x0D]+``, and for each text the index of its first word (n + 1 entries)."""
        solid = ~IS_SPACE[self.data]
        n = len(solid)
        if n == 0:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(self) + 1, np.int64)
        first = np.empty(n, bool)
        first[0] = True
        first[1:] = ~solid[:-1]
        inner = self.off[:-1]
        first[inner[inner < n]] = True
        last = np.empty(n, bool)
        last[-1] = True
        last[:-1] = ~solid[1:]
        ends = self.off[1:]
        last[ends[ends > 0] - 1] = True
        start, end = np.flatnonzero(solid & first), np.flatnonzero(solid & last) + 1
        return start, end, np.searchsorted(start, self.off)

    def lines(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of the pieces between line feeds, and for each text the index of its first piece."""
        feeds = np.flatnonzero(self.data == 10)
        k = np.searchsorted(feeds, self.off)
        at = k + np.arange(len(k))
        total = len(feeds) + len(self)
        start, end = np.empty(total, np.int64), np.empty(total, np.int64)
        opened = np.ones(total, bool)
        opened[at[:-1]] = False
        start[at[:-1]] = self.off[:-1]
        start[opened] = feeds + 1
        closed = np.ones(total, bool)
        closed[at[1:] - 1] = False
        end[at[1:] - 1] = self.off[1:]
        end[closed] = feeds
        return start, end, at


def word_shingles(word_hash: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k consecutive words, and for each text the index of its first shingle.

    A text of fewer than k words, but at least one, has one shingle: all its words.
    """
    n = np.diff(first)
    count = np.where(n >= k, n - k + 1, (n > 0).astype(np.int64))
    at = np.concatenate([[0], np.cumsum(count)])
    texts = np.repeat(np.arange(len(n)), count)
    begin = first[:-1][texts] + (np.arange(at[-1]) - at[:-1][texts])
    words = np.minimum(n[texts], k)
    out = mix64(words.astype(np.uint64) * _ODD[3])
    for j in range(k):
        has = words > j
        if has.all():
            out = _absorb(out, word_hash[begin + j], 0)
        else:
            out[has] = _absorb(out[has], word_hash[begin[has] + j], 0)
    return out, at


def shingle_sets(chunk: TextChunk, k: int) -> Iterator[np.ndarray]:
    """For each text its sorted distinct k-word shingles of the A-Z-lower-cased words."""
    start, end, first = chunk.words()
    hashes, at = word_shingles(chunk.span_hash(start, end, lower=True), first, k)
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        own = np.sort(hashes[a:b])
        if len(own) > 1:
            own = own[np.concatenate([[True], own[1:] != own[:-1]])]
        yield own


def chunks(batch: pa.RecordBatch, text: str, limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, TextChunk]]:
    """Slices of whole rows with up to ``limit`` bytes of text each (a longer text stands alone)."""
    column = batch.column(batch.schema.get_field_index(text))
    if len(column) == 0:
        return
    size = np.asarray(pc.fill_null(pc.binary_length(column), 0), dtype=np.int64)
    total = np.concatenate([[0], np.cumsum(size)])
    a = 0
    while a < len(size):
        b = max(a + 1, int(np.searchsorted(total, total[a] + limit, "right")) - 1)
        part = batch.slice(a, b - a)
        yield part, TextChunk.of(part.column(part.schema.get_field_index(text)))
        a = b


def all_chunks(batches: Iterable[pa.RecordBatch], text: str = "text", limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, TextChunk]]:
    for batch in batches:
        yield from chunks(batch, text, limit)


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
