"""Array forms of text: words, word hashes and shingles of a whole Arrow column at once.

Every function works on UTF-8 bytes held in one buffer, so a text of any length is read whole and no
Python object is made per word. A word is a longest run of bytes other than 0x20 and 0x09-0x0D, after
lower-casing A-Z only; a null text counts as empty.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text handled at a time; a longer text forms a chunk of its own.
CHUNK_BYTES = 1 << 19
#: Texts handled at a time.
CHUNK_ROWS = 1024

_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[32, *range(9, 14)]] = True
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers whose output bits all depend on all input bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _power(base: np.uint64, n: int) -> np.ndarray:
    key = str(base)
    have = _powers.get(key)
    if have is None or len(have) < n:
        have = np.full(max(n, CHUNK_BYTES + 1), base, dtype=np.uint64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        if len(have) <= 4 * CHUNK_BYTES:
            _powers[key] = have
    return have[:n]


def column_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null has length zero."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    column = column.fill_null("") if column.null_count else column
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(column) + 1, dtype=np.int64)
    offsets = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, dtype=np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of at most CHUNK_ROWS rows whose texts hold at most `limit` bytes together, or one row each."""
    n, row = len(offsets) - 1, 0
    while row < n:
        to = max(row + 1, int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1)
        to = min(to, n, row + CHUNK_ROWS)
        yield row, to
        row = to


def release() -> None:
    """Hands freed memory back to the system: idle worker processes outlive the stage they worked for."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


class Words:
    """The words of the texts of some rows.

    `data` the bytes (lower-cased unless `lower` is false), `start` and `end` of each word therein, `row` its text's number,
    `first` the number of the first word of each text (with one more entry at the end).
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, lower: bool = True) -> None:
        self.data = _LOWER[data] if lower else data
        space = _IS_SPACE[data]
        edge = np.ones(len(data) + 1, dtype=bool)  # a word cannot go on from the position before
        if len(data):
            edge[1:-1] = space[:-1]
        edge[offsets] = True
        begins = edge[:-1] & ~space
        ends = np.ones(len(data), dtype=bool)
        if len(data):
            ends[:-1] = space[1:]
            cut = offsets[(offsets > 0) & (offsets <= len(data))] - 1
            ends[cut] = True
        self.start = np.flatnonzero(begins)
        self.end = np.flatnonzero(ends & ~space) + 1
        self.first = np.searchsorted(self.start, offsets)
        self.count = np.diff(self.first)
        self.row = np.repeat(np.arange(len(offsets) - 1), self.count)

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word."""
        n = len(self.data)
        if not len(self.start):
            return np.zeros(0, dtype=np.uint64)
        total = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * _power(_BASE, n), out=total[1:])
        h = (total[self.end] - total[self.start]) * _power(_BASE_INV, n)[self.start]
        return mix(h + (self.end - self.start).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))

    def shingles(self, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
        """(hash, row) of every run of `width` words; of a shorter text, its whole sequence as one."""
        h = self.hashes()
        if not len(h):
            return h, self.row
        place = np.arange(len(h)) - self.first[self.row]
        left = self.count[self.row] - place
        take = (left >= width) | (place == 0)
        at = np.flatnonzero(take)
        size = np.minimum(self.count[self.row[at]], width)
        out = mix(size.astype(np.uint64) * _BASE)
        for k in range(width):
            has = size > k
            if has.all():
                out = mix(out * _BASE + h[at + k])
            else:
                out[has] = mix(out[has] * _BASE + h[at[has] + k])
        return out, self.row[at]


def texts(column: pa.Array | pa.ChunkedArray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, last row + 1, bytes, offsets) for each chunk of a string column."""
    data, offsets = column_bytes(column)
    for a, b in chunks(offsets, limit):
        yield a, b, data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
    del data, offsets
    release()
