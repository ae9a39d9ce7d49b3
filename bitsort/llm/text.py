"""Vectorised word splitting and rolling hashes over Arrow string columns.

Everything here works on a *chunk*: the UTF-8 bytes of several documents back to back plus the
byte offset of each document.  Polynomial (Rabin-Karp) hashes are prefix sums modulo 2**64, so a
hash of any byte or word range costs one subtraction and one multiplication; a final bit mixer
spreads them.  Nulls count as empty texts.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

U64 = np.uint64
# Workers live on between tasks: Arrow takes memory from the C library, and ``trim`` hands back what is free.
pa.set_memory_pool(pa.system_memory_pool())
_LIBC = ctypes.CDLL(None)


#: Functions that drop what a worker process keeps between tasks.
CACHES: list = []


def release() -> None:
    """Drop the caches that earlier operators left in this worker; for operators that need the room."""
    for clear in CACHES:
        clear()
    trim()


def trim() -> None:
    """Give free memory of this process back to the system, where the C library can."""
    if hasattr(_LIBC, "malloc_trim"):
        _LIBC.malloc_trim(0)


#: Odd multipliers of the byte and the word polynomial; any odd value works, both sides must agree.
BYTE_BASE = 0x9E3779B97F4A7C15
WORD_BASE = 0xD6E8FEB86659FD93
CHUNK_BYTES = 1 << 20


def _lut(flags) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[list(flags)] = True
    return out


#: Bytes that part words: ASCII white space, or everything in ASCII that is no letter or digit.
WHITE = _lut([0x20, *range(0x09, 0x0E)])
NOT_ALNUM = _lut([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse, self.n = base, pow(base, -1, 1 << 64), 0
        self.up = self.down = np.ones(0, dtype=U64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > self.n:
            self.n = max(n, 2 * self.n, 1 << 12)
            with np.errstate(over="ignore"):
                for name, step in (("up", self.base), ("down", self.inverse)):
                    a = np.full(self.n, step, dtype=U64)
                    a[0] = 1
                    setattr(self, name, np.multiply.accumulate(a))
        return self.up[:n], self.down[:n]


_BYTES, _WORDS = _Powers(BYTE_BASE), _Powers(WORD_BASE)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every input bit over the output."""
    with np.errstate(over="ignore"):
        h = h ^ (h >> U64(33))
        h *= U64(0xFF51AFD7ED558CCD)
        h ^= h >> U64(33)
        h *= U64(0xC4CEB9FE1A85EC53)
        h ^= h >> U64(33)
    return h


@dataclass
class Chunk:
    """Documents ``first .. first+len(ptr)-2`` of a batch, cut into words.

    ``start``/``end``: byte range of each word in ``data``; words of document ``i`` are
    ``ptr[i]:ptr[i+1]``, its bytes ``edges[i]:edges[i+1]``.
    """

    first: int
    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    ptr: np.ndarray
    edges: np.ndarray

    def doc_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ptr) - 1), np.diff(self.ptr))

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of every word's bytes."""
        n = len(self.data)
        up, down = _BYTES.get(n + 1)
        with np.errstate(over="ignore"):
            total = np.zeros(n + 1, dtype=U64)
            np.cumsum((self.data.astype(U64) + U64(1)) * up[:n], out=total[1:])
            raw = (total[self.end] - total[self.start]) * down[self.start]
            return mix(raw ^ ((self.end - self.start).astype(U64) * U64(0xA24BAED4963EE407)))

    def windows(self, k: int, words: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(index of the first word, hash) of every run of ``k`` words inside one document."""
        words = self.hashes() if words is None else words
        n = len(words)
        if n < k:
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=U64)
        at = window_starts(self.ptr, k)
        return at, window_hashes(words, k)[at]


def window_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Rabin-Karp hash of words[p:p+k] for every p, document borders ignored."""
    n = len(words)
    up, down = _WORDS.get(n + 1)
    with np.errstate(over="ignore"):
        total = np.zeros(n + 1, dtype=U64)
        np.cumsum(words * up[:n], out=total[1:])
        return mix((total[k:] - total[: n + 1 - k]) * down[: n + 1 - k] + U64(k))


def window_starts(ptr: np.ndarray, k: int) -> np.ndarray:
    """Word indexes at which a run of k words fits into its document."""
    free = np.maximum(np.diff(ptr) - k + 1, 0)
    total = int(free.sum())
    return np.repeat(ptr[:-1] - (np.cumsum(free) - free), free) + np.arange(total)


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary array; null entries are empty."""
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    column = column.cast(pa.large_binary())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    return (np.frombuffer(data, dtype=np.uint8) if data is not None and len(data) else np.zeros(0, dtype=np.uint8)), offsets


def split_words(data: np.ndarray, offsets: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, ptr) of the words of documents that lie back to back in ``data`` from 0 on."""
    inside = np.zeros(len(data) + 2, dtype=np.int8)
    inside[1:-1] = ~breaks[data]
    edge = np.diff(inside)
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    cut = offsets[1:-1]
    cut = np.unique(cut[(cut > 0) & (cut < len(data))])
    cut = cut[(inside[cut] == 1) & (inside[cut + 1] == 1)]  # a border in the middle of a run of word bytes
    if len(cut):
        start, end = np.sort(np.concatenate([start, cut])), np.sort(np.concatenate([end, cut]))
    return start, end, np.searchsorted(start, offsets)


def chunks(column: pa.Array, breaks: np.ndarray = WHITE, lower: bool = False, size: int = CHUNK_BYTES) -> Iterator[Chunk]:
    """Cut a column into chunks of whole documents of about ``size`` bytes."""
    data, offsets = string_buffers(column)
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, side="right")) - 1)
        part, off = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        part = LOWER[part] if lower else part
        yield Chunk(i, part, *split_words(part, off, breaks), off)
        i = j


def sorted_unique(values: np.ndarray) -> np.ndarray:
    values = np.sort(values)
    return values[np.concatenate([[True], values[1:] != values[:-1]])] if len(values) else values


def binaries(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """A binary array over ``data`` (any dtype) whose i-th entry ends at item ``ends[i]``."""
    offsets = np.concatenate([[0], ends]).astype(np.int64) * data.dtype.itemsize
    flat = np.ascontiguousarray(data).tobytes()
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(flat)]).cast(pa.binary())
