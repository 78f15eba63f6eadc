"""Texts as flat numpy arrays: words, lines and windows of words as 64-bit hashes, without a Python loop over words.

A *word* is a run of bytes outside ``[\\x20\\x09-\\x0D]``; that class is ASCII, so UTF-8 can be cut bytewise.
Null counts as the empty text everywhere.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_BASE = 0x9E3779B97F4A7C15
_WORD_BASE = 0xD1B54A32D192ED03
CHUNK_BYTES = 1 << 19
#: Where each distinct word of a chunk is worked on once.
WORD_CHUNK_BYTES = 2 << 20


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of a counter generator: a bijection on 64 bits with good avalanche."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def mix_int(x: int) -> int:
    return int(mix64(np.array([x & (1 << 64) - 1], np.uint64))[0])


def unit(x: np.ndarray) -> np.ndarray:
    """Hashes to (0, 1)."""
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) * (1.0 / (1 << 53))


def trim() -> None:
    """Hand memory that was freed back to the system: workers live on from stage to stage, beside the JVM's heap."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


class _Powers:
    def __init__(self, base: int) -> None:
        self.base, self.up, self.down = base, np.ones(1, np.uint64), np.ones(1, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << (n - 1).bit_length()
            for name, b in (("up", self.base), ("down", pow(self.base, -1, 1 << 64))):
                a = np.full(size, b, np.uint64)
                a[0] = 1
                setattr(self, name, np.multiply.accumulate(a))
        return self.up, self.down


_bytes_pow, _words_pow = _Powers(_BASE), _Powers(_WORD_BASE)


@dataclass
class Chunk:
    """Rows lo..hi of a column: their bytes and row offsets."""

    lo: int
    hi: int
    data: np.ndarray
    offs: np.ndarray

    @property
    def n(self) -> int:
        return self.hi - self.lo

    def text(self, i: int) -> bytes:
        return self.data[self.offs[i] : self.offs[i + 1]].tobytes()


def flat(col: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary column; null is empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
        if isinstance(col, pa.ChunkedArray):
            col = pa.concat_arrays(col.chunks) if col.num_chunks else pa.array([], col.type)
    if pa.types.is_null(col.type):
        return np.zeros(0, np.uint8), np.zeros(len(col) + 1, np.int64)
    if col.null_count:
        col = col.fill_null(b"" if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else "")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, ob, db = col.buffers()
    offs = np.frombuffer(ob, np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64) if ob is not None and len(col) else np.zeros(len(col) + 1, np.int64)
    data = np.frombuffer(db, np.uint8) if db is not None else np.zeros(0, np.uint8)
    return data[offs[0] : offs[-1]], offs - offs[0]


def chunks(col: pa.Array | pa.ChunkedArray, limit: int = CHUNK_BYTES) -> Iterator[Chunk]:
    """Cut a column into runs of rows of at most ``limit`` bytes (a longer text is a chunk of its own)."""
    data, offs = flat(col)
    lo, n = 0, len(offs) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + limit, "right")) - 1)
        yield Chunk(lo, hi, data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo])
        lo = hi


@dataclass
class Words:
    """All words of a chunk. ``first[i]:first[i+1]`` are those of row i."""

    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    hash: np.ndarray | None = None

    @property
    def count(self) -> np.ndarray:
        return np.diff(self.first)

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.count)


def prefix_hash(data: np.ndarray) -> np.ndarray:
    up, _ = _bytes_pow.get(len(data) + 1)
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans, equal for equal bytes wherever they stand."""
    _, down = _bytes_pow.get(len(prefix))
    return mix64((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64) * np.uint64(0xA0761D6478BD642F))


def words(c: Chunk, hashed: bool = True, prefix: np.ndarray | None = None, separators: np.ndarray = SPACE) -> Words:
    n = len(c.data)
    if not n:
        z = np.zeros(0, np.int64)
        return Words(z, z, np.zeros(c.n + 1, np.int64), np.zeros(0, np.uint64) if hashed else None)
    inside = ~separators[c.data]
    edge = np.zeros(n + 1, bool)  # a row begins here
    edge[c.offs] = True
    before = np.empty(n + 1, bool)
    before[0] = False
    before[1:] = inside
    here = np.empty(n + 1, bool)
    here[:-1] = inside
    here[-1] = False
    start = np.flatnonzero(here & (~before | edge))
    end = np.flatnonzero(before & (~here | edge))
    out = Words(start, end, np.searchsorted(start, c.offs))
    if hashed:
        out.hash = span_hash(prefix_hash(c.data) if prefix is None else prefix, start, end)
    return out


def windows(w: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of ``size`` consecutive words of one row, for each position where such a window fits, and a mask of those positions.

    The hash array has an entry for each word; those outside the mask mean nothing.
    """
    n = len(w.start)
    up, down = _words_pow.get(n + 1)
    pre = np.zeros(n + 1, np.uint64)
    np.cumsum(w.hash * up[:n], out=pre[1:])
    out, fits = np.zeros(n, np.uint64), np.zeros(n, bool)
    if n >= size:
        out[: n - size + 1] = mix64((pre[size:] - pre[: n - size + 1]) * down[: n - size + 1] + np.uint64(size))
        last = np.repeat(w.first[1:], w.count)
        fits = np.arange(n) + size <= last
    return out, fits


def whole(w: Words, salt: int = 0) -> np.ndarray:
    """A hash of each row's whole word sequence (0 words: 0)."""
    n = len(w.start)
    up, down = _words_pow.get(n + 1)
    pre = np.zeros(n + 1, np.uint64)
    np.cumsum(mix64(w.hash + np.uint64(salt)) * up[:n], out=pre[1:])
    a, b = w.first[:-1], w.first[1:]
    out = mix64((pre[b] - pre[a]) * down[a] + (b - a).astype(np.uint64) * np.uint64(0xE7037ED1A0B428DB))
    out[a == b] = 0
    return out


def covered(n: int, starts: np.ndarray, size: int) -> np.ndarray:
    """Mask of the n positions that lie in a window of ``size`` at one of ``starts``."""
    d = np.bincount(starts, minlength=n + 1) - np.bincount(starts + size, minlength=n + 1)
    return np.cumsum(d[:n]) > 0
