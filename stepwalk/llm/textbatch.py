"""Array views of text batches: words, word hashes and window hashes without a Python loop over words.

A word is a maximal run of bytes other than space and 0x09-0x0D.  Hashes are 64-bit polynomial prefix sums (arithmetic
wraps modulo 2**64 and the base is odd, so a span's hash is a difference of two sums times an inverse power) followed by
a bit mix.  Every function takes whole texts; nothing is cut to a prefix.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 20
U64 = np.uint64

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse, self.size = base, pow(base, -1, 1 << 64), 0
        self.up = self.down = np.ones(1, dtype=U64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > self.size:
            self.size = max(n, 1 << 16)
            up = np.full(self.size, self.base, dtype=U64)
            down = np.full(self.size, self.inverse, dtype=U64)
            up[0] = down[0] = 1
            self.up, self.down = np.cumprod(up), np.cumprod(down)
        return self.up[:n], self.down[:n]


BYTES = Powers(0x9E3779B97F4A7C15)
WORDS = Powers(0xD1342543DE82EF95)


def mix(h: np.ndarray) -> np.ndarray:
    """Bijective finaliser on 64-bit values."""
    h = h ^ (h >> U64(32))
    h = h * U64(0xD6E8FEB86659FD93)
    h ^= h >> U64(29)
    h *= U64(0xBF58476D1CE4E5B9)
    h ^= h >> U64(32)
    return h


def span_sums(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Polynomial of each span's bytes, its first byte the constant term."""
    if not len(start):
        return np.zeros(0, U64)
    up, down = BYTES.upto(len(data))
    sums = np.zeros(len(data) + 1, U64)
    np.cumsum(up * (data.astype(U64) + U64(1)), out=sums[1:])
    return (sums[end] - sums[start]) * down[start]


class Chunk:
    """Some rows of a batch with the bytes of one text column (nulls count as empty)."""

    def __init__(self, rows: pa.RecordBatch, column: str = "text"):
        self.rows = rows
        texts = rows.column(rows.schema.get_field_index(column))
        self.null = np.asarray(texts.is_null())
        if texts.null_count:
            texts = pc.fill_null(texts, "")
        texts = texts.cast(pa.large_binary())
        _, offsets, data = texts.buffers()
        at = np.frombuffer(offsets, dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1] if offsets else np.zeros(1, np.int64)
        body = np.frombuffer(data, dtype=np.uint8) if data else np.zeros(0, np.uint8)
        self.bytes = body[at[0] : at[-1]]
        self.offsets = at - at[0]
        self.n = len(texts)

    def ints(self, column: str) -> np.ndarray:
        """An integer column, nulls as 0."""
        values = self.rows.column(self.rows.schema.get_field_index(column))
        return np.asarray(pc.fill_null(values, 0) if values.null_count else values)

    def text(self, k: int) -> bytes:
        return self.bytes[self.offsets[k] : self.offsets[k + 1]].tobytes()

    def words(self) -> Words:
        return Words(self)


class Words:
    """Byte spans of the words of a chunk, in order; ``doc`` is the row of each, ``first`` the first word of each row."""

    def __init__(self, chunk: Chunk):
        data, at = chunk.bytes, chunk.offsets
        self.chunk = chunk
        gap = _SPACE[data]
        n = len(data)
        before = np.ones(n, dtype=bool)
        before[1:] = gap[:-1]
        after = np.ones(n, dtype=bool)
        after[:-1] = gap[1:]
        inner = at[(at > 0) & (at < n)]
        before[inner] = True
        after[inner - 1] = True
        solid = ~gap
        self.start = np.flatnonzero(solid & before)
        self.end = np.flatnonzero(solid & after) + 1
        self.first = np.searchsorted(self.start, at)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(chunk.n), self.count)

    def hashes(self) -> np.ndarray:
        return mix(span_sums(self.chunk.bytes, self.start, self.end))

    def windows(self, hashes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(first word, hash) of every window of ``size`` consecutive words of one row."""
        n = len(hashes)
        if n < size:
            return np.zeros(0, np.int64), np.zeros(0, U64)
        up, down = WORDS.upto(n)
        sums = np.zeros(n + 1, U64)
        np.cumsum(up * hashes, out=sums[1:])
        first = np.flatnonzero(self.doc[: n - size + 1] == self.doc[size - 1 :])
        return first, mix((sums[first + size] - sums[first]) * down[first] + U64(size))


def give_back() -> None:
    """Hands freed memory back to the system, where the C library can: an idle worker then keeps little."""
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):
        pass


def chunks(batches, column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[Chunk]:
    """Batches cut between rows so that a chunk has at most ``limit`` text bytes (one longer text stands alone)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        texts = batch.column(batch.schema.get_field_index(column))
        size = np.asarray(pc.fill_null(pc.binary_length(texts), 0)).astype(np.int64)
        total = np.concatenate([[0], np.cumsum(size)])
        at = 0
        while at < batch.num_rows:
            to = int(np.searchsorted(total, total[at] + limit, side="right")) - 1
            to = min(max(to, at + 1), batch.num_rows)
            yield Chunk(batch.slice(at, to - at), column)
            at = to
        del batch, texts
        pa.default_memory_pool().release_unused()
    give_back()


_KEPT: dict = {}


def kept_in_worker(key, make):
    """An object that outlives a task in its Python worker.  One is kept: the next operator's replaces it."""
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = make()
    return _KEPT[key]


def let_go() -> None:
    """Drops what an operator before kept in this worker, for operators that keep nothing of their own."""
    _KEPT.clear()


class KnownWords:
    """Ids of words seen before, in arrays sorted by word hash: at most ``limit`` words are kept, others are encoded each time."""

    def __init__(self, encode, limit: int = 200_000):
        self.encode, self.limit = encode, limit
        self.known = np.zeros(0, U64)
        self.at = np.zeros(0, np.int64)
        self.len = np.zeros(0, np.int64)
        self.ids = np.zeros(0, np.int32)

    def __call__(self, hashes: np.ndarray, word) -> tuple[np.ndarray, np.ndarray]:
        """(ids one after the other, ids per word) of words with these hashes; ``word(k)`` gives the bytes of word k."""
        unique, first, back = np.unique(hashes, return_index=True, return_inverse=True)
        place = np.searchsorted(self.known, unique)
        place[place == len(self.known)] = 0
        found = self.known[place] == unique if len(self.known) else np.zeros(len(unique), bool)
        new = np.flatnonzero(~found)
        ids, size = self.encode([word(k) for k in first[new].tolist()])
        at, length = np.empty(len(unique), np.int64), np.empty(len(unique), np.int64)
        at[found], length[found] = self.at[place[found]], self.len[place[found]]
        at[new], length[new] = np.cumsum(size) - size + len(self.ids), size
        pool = np.concatenate([self.ids, ids])
        if len(new) and len(self.known) + len(new) <= self.limit:
            keys = np.concatenate([self.known, unique[new]])
            order = np.argsort(keys, kind="stable")
            self.at = np.concatenate([self.at, at[new]])[order]
            self.len = np.concatenate([self.len, size])[order]
            self.known, self.ids = keys[order], pool
        per = length[back]
        return pool[ragged(at[back], per)], per


def repeated_cover(words: Words, hashes: np.ndarray, size: int = 3) -> np.ndarray:
    """Words inside a window of ``size`` words that their row holds at least twice."""
    first, window = words.windows(hashes, size)
    cover = np.zeros(len(hashes) + size, np.int64)
    if len(first):
        own = mix(window ^ (words.doc[first].astype(U64) * U64(0x9E3779B97F4A7C15)))
        order = np.argsort(own, kind="stable")
        same = own[order][1:] == own[order][:-1]
        twice = np.zeros(len(own), bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        hit = first[twice]
        np.add.at(cover, hit, 1)
        np.add.at(cover, hit + size, -1)
    return np.cumsum(cover)[: len(hashes)] > 0


def runs(lengths: np.ndarray) -> np.ndarray:
    """0..n-1 for each length n, one after the other."""
    total = int(lengths.sum())
    ends = np.cumsum(lengths)
    return np.arange(total) - np.repeat(ends - lengths, lengths)


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices start..start+length-1 of each span, one after the other."""
    return np.repeat(starts, lengths) + runs(lengths)


def uint64_blob(values: np.ndarray) -> bytes:
    return np.ascontiguousarray(values, dtype="<u8").tobytes()
