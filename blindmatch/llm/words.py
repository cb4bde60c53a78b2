"""Words of whole texts as numpy arrays, for a chunk of documents at a time.

A word is a maximal run of bytes other than space, tab, line feed, vertical tab, form feed and
carriage return. UTF-8 never uses those bytes inside a longer code point, so words of bytes are words of text.
"""

from __future__ import annotations

import ctypes
import functools
import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa

WORD = r"[^\x20\x09-\x0D]+"
#: Text bytes handled at once; one longer document makes a chunk of its own.
CHUNK_BYTES = 2 << 20
LONG_WORD = 64

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class Words:
    """Words of a chunk: ``data`` bytes, ``start``/``end`` of each word, ``first[d]:first[d + 1]`` of document d."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data, self.offsets = data, offsets
        inside = ~_SPACE[data]
        begin = inside.copy()
        begin[1:] &= ~inside[:-1]
        stop = inside.copy()
        stop[:-1] &= ~inside[1:]
        edge = offsets[1:-1]
        edge = edge[(edge > 0) & (edge < len(data))]
        begin[edge] = inside[edge]
        stop[edge - 1] = inside[edge - 1]
        self.start = np.flatnonzero(begin)
        self.end = np.flatnonzero(stop) + 1
        self.first = np.searchsorted(self.start, offsets)
        self.n_docs = len(offsets) - 1

    def __len__(self) -> int:
        return len(self.start)

    def doc(self) -> np.ndarray:
        """The document's index of each word."""
        return np.repeat(np.arange(self.n_docs), np.diff(self.first))

    def hashes(self, data: np.ndarray | None = None, seed: int = 0) -> np.ndarray:
        """64-bit hashes of the words' bytes, taken from ``data`` where a changed copy is given."""
        data = self.data if data is None else data
        size = self.end - self.start
        out = np.full(len(size), (0xCBF29CE484222325 ^ (seed * 0x9E3779B97F4A7C15)) & (2**64 - 1), _U)
        order = np.argsort(-np.minimum(size, LONG_WORD + 1), kind="stable")
        begin, size = self.start[order], size[order]
        n_long = int(np.searchsorted(-size, -LONG_WORD, side="left"))
        h = out[order]
        for k in range(int(size[n_long]) if n_long < len(size) else 0):
            live = int(np.searchsorted(-size, -k, side="left"))
            part = h[n_long:live]
            h[n_long:live] = (part ^ data[begin[n_long:live] + k]) * _U(0x100000001B3)
        raw = data.tobytes() if n_long else b""
        for i in range(n_long):
            digest = hashlib.blake2b(raw[begin[i] : begin[i] + size[i]], digest_size=8, key=b"%d" % seed)
            h[i] = int.from_bytes(digest.digest(), "little")
        out[order] = h
        return mix(out ^ mix((self.end - self.start).astype(_U)))

    def windows(self, hashes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of k consecutive words of one document, by their first word; and which of them stay in it."""
        n = len(hashes) - k + 1
        if n <= 0:
            return np.zeros(0, _U), np.zeros(0, bool)
        out = np.zeros(n, _U)
        for j in range(k):
            out = out * _U(0xD6E8FEB86659FD93) + hashes[j : j + n]
        inside = np.ones(n, bool)
        for cut in np.unique(self.first[1:-1]):
            inside[max(0, cut - k + 1) : cut] = False
        return mix(out), inside


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; nulls are empty."""
    column = column.fill_null("") if column.null_count else column
    wide = pa.types.is_large_string(column.type)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32)
    offsets = offsets[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    return np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8), offsets


def chunks(column: pa.Array, size: int = CHUNK_BYTES) -> Iterator[tuple[int, int, Words]]:
    """Rows ``low:high`` of a string column and their words, about ``size`` bytes at a time."""
    if len(column) == 0:
        return
    data, offsets = text_buffers(column)
    low = 0
    while low < len(column):
        high = int(np.searchsorted(offsets, offsets[low] + size, side="right")) - 1
        high = min(max(high, low + 1), len(column))
        yield low, high, Words(data[offsets[low] : offsets[high]], offsets[low : high + 1] - offsets[low])
        low = high


def lower_ascii(data: np.ndarray) -> np.ndarray:
    """A copy with A-Z as a-z; bytes of longer code points are never in that range."""
    out = data.copy()
    out[(out >= 65) & (out <= 90)] += 32
    return out


def give_back() -> None:
    """Freed memory of this process goes back to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def lean(rows: Callable) -> Callable:
    """``rows`` for mapInArrow; when its input ends, memory is given back, as workers live on between tasks."""

    @functools.wraps(rows)
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from rows(batches)
        finally:
            give_back()

    return run


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
