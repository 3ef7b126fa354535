"""Vectorised text kernels shared by the corpus operators.

A `Block` holds a few megabytes of UTF-8 text of whole documents and finds words, word hashes and
n-gram hashes with numpy only, so that no Python object is made for each word. Nulls count as empty texts.
Hashes have 64 bits and are equal on all machines; equal hashes are taken as equal words or n-grams.
"""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1_500_000
_MASK = (1 << 64) - 1
MAX64 = np.uint64(_MASK)


def _splitmix(seed: int, n: int) -> np.ndarray:
    out = []
    for _ in range(n):
        seed = (seed + 0x9E3779B97F4A7C15) & _MASK
        z = seed
        z = ((z ^ (z >> 30)) * 0xBF58476D1CE4E5B9) & _MASK
        z = ((z ^ (z >> 27)) * 0x94D049BB133111EB) & _MASK
        out.append(z ^ (z >> 31))
    return np.array(out, dtype=np.uint64)


_BYTE_CODE = _splitmix(11, 256)
_GRAM_CODE = _splitmix(23, 64) | np.uint64(1)
_BASE = 0xD1342543DE82EF95
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: tuple[np.ndarray, np.ndarray] = (np.ones(1, np.uint64), np.ones(1, np.uint64))

_bytes = np.arange(256)
#: Words are runs of bytes outside 0x20 and 0x09-0x0D.
SPACE_WORDS = ~((_bytes == 0x20) | ((_bytes >= 9) & (_bytes <= 13)))
#: Words are runs of ASCII digits, ASCII letters and bytes of other characters.
ALNUM_WORDS = ((_bytes >= 48) & (_bytes <= 57)) | ((_bytes >= 65) & (_bytes <= 90)) | ((_bytes >= 97) & (_bytes <= 122)) | (_bytes >= 128)
LOWER = np.where((_bytes >= 65) & (_bytes <= 90), _bytes + 32, _bytes).astype(np.uint8)
_FIRST_BYTE = ((_bytes & 0xC0) != 0x80)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads all bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def mix_int(x: int) -> int:
    return int(mix(np.array([x & _MASK], dtype=np.uint64))[0])


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        out = []
        for base in (_BASE, _INVERSE):
            p = np.full(n, base, np.uint64)
            p[0] = 1
            out.append(np.cumprod(p))
        _powers = (out[0], out[1])
    return _powers


def starts_of(sizes: np.ndarray) -> np.ndarray:
    out = np.zeros(len(sizes) + 1, np.int64)
    np.cumsum(sizes, out=out[1:])
    return out


def sums_by(values: np.ndarray, ptr: np.ndarray) -> np.ndarray:
    """Sums of values[ptr[i]:ptr[i+1]]; empty ranges give 0."""
    total = np.zeros(len(values) + 1, np.float64 if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=total[1:])
    return total[ptr[1:]] - total[ptr[:-1]]


def lean(f: Callable[..., Iterator[pa.RecordBatch]]) -> Callable[..., Iterator[pa.RecordBatch]]:
    """f, after which free memory goes back to the system: Python workers stay for later tasks and would keep it."""

    @functools.wraps(f)
    def run(*args):
        yield from f(*args)
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
        if trim:
            trim(0)

    return run


class Block:
    """Bytes of whole documents, `offsets` (one more than documents) into them, and their words."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, words: np.ndarray = SPACE_WORDS, lower: bool = False):
        self.raw, self.offsets = data, offsets
        self.data = LOWER[data] if lower else data
        self.n_docs, n = len(offsets) - 1, len(data)
        inside = words[data]
        self.inside = inside
        edge = np.zeros(n + 1, bool)
        edge[offsets] = True
        before = np.empty(n, bool)
        before[:1] = True
        np.logical_or(~inside[:-1], edge[1:n], out=before[1:])
        self.start = np.flatnonzero(inside & before)
        after = np.empty(n, bool)
        after[-1:] = True
        np.logical_or(~inside[1:], edge[1:n], out=after[:-1])
        self.end = np.flatnonzero(inside & after) + 1
        self.ptr = np.searchsorted(self.start, offsets)
        self.n_words = np.diff(self.ptr)
        self._prefix: np.ndarray | None = None
        self._hash: np.ndarray | None = None

    @property
    def doc(self) -> np.ndarray:
        """The document, by place in the block, of each word."""
        return np.repeat(np.arange(self.n_docs), self.n_words)

    def range_hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Hashes of byte ranges; each depends on the bytes alone."""
        n = len(self.data)
        power, inverse = _power_tables(max(n, 1))
        if self._prefix is None:
            self._prefix = np.zeros(n + 1, np.uint64)
            np.cumsum(_BYTE_CODE[self.data] * power[:n], out=self._prefix[1:])
        return mix((self._prefix[end] - self._prefix[start]) * inverse[np.minimum(start, n - 1)] + (end - start).astype(np.uint64)) if n else np.zeros(len(start), np.uint64)

    @property
    def hash(self) -> np.ndarray:
        if self._hash is None:
            self._hash = self.range_hash(self.start, self.end)
            self._prefix = None
        return self._hash

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of the n words from each word on, and whether they lie in one document. As long as the words."""
        h, m = self.hash, len(self.hash)
        out, good = np.full(m, MAX64, np.uint64), np.zeros(m, bool)
        if m >= n:
            total = np.zeros(m - n + 1, np.uint64)
            for k in range(n):
                total += h[k : m - n + 1 + k] * _GRAM_CODE[k % 64] * np.uint64(1 + 2 * (k // 64))
            last = np.repeat(self.ptr[1:], self.n_words)
            good[: m - n + 1] = np.arange(m - n + 1) + n <= last[: m - n + 1]
            out[: m - n + 1][good[: m - n + 1]] = mix(total[good[: m - n + 1]] + np.uint64(n))
        return out, good

    def characters(self) -> np.ndarray:
        """Code points inside words, by document."""
        return sums_by((self.inside & _FIRST_BYTE[self.data]).astype(np.int64), self.offsets)

    def text(self, i: int) -> bytes:
        return self.raw[self.offsets[i] : self.offsets[i + 1]].tobytes()


def text_arrays(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(buffers[2], np.uint8)[offsets[0] : offsets[-1]] if buffers[2] is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def blocks(column: pa.Array, words: np.ndarray = SPACE_WORDS, lower: bool = False, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int, Block]]:
    """(first row, row after the last, Block) over a column; a block has one text at least and about `size` bytes at most otherwise."""
    data, offsets = text_arrays(column)
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + size, side="right")) - 1)
        j = min(j, n)
        yield i, j, Block(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], words, lower)
        i = j


def sliding(values: np.ndarray, width: int, of=np.minimum, fill=MAX64) -> np.ndarray:
    """of() over values[i : i + width]; places past the end count as `fill`."""
    out, done = values, 1
    while done < width:
        step = min(done, width - done)
        moved = np.full(len(out), fill, out.dtype)
        moved[: max(0, len(out) - step)] = out[step:]
        out, done = of(out, moved), done + step
    return out


def repeated(keys: np.ndarray) -> np.ndarray:
    """True where a key occurs more than once."""
    order = np.argsort(keys, kind="stable")
    s = keys[order]
    same = np.zeros(len(s) + 1, bool)
    same[1:-1] = s[1:] == s[:-1]
    out = np.empty(len(s), bool)
    out[order] = same[1:] | same[:-1]
    return out


def covered(at: np.ndarray, width: int, n: int) -> np.ndarray:
    """True for each of n places inside [p, p + width) of some p."""
    step = np.zeros(n + 1, np.int32)
    np.add.at(step, at, 1)
    np.add.at(step, np.minimum(at + width, n), -1)
    return np.cumsum(step[:-1]) > 0
