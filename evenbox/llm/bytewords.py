"""Vectorised word scanning of Arrow text columns.

A word is a maximal run of characters other than U+0020 and U+0009..U+000D. Those separators are
single bytes in UTF-8, so words are found on the raw bytes of a whole slice of rows at once; a row
boundary separates words as well. Words and word windows are named by 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15)
_MIX1 = np.uint64(0xBF58476D1CE4E5B9)
_MIX2 = np.uint64(0x94D049BB133111EB)
_powers: dict[str, np.ndarray] = {}


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64, so that every output bit depends on every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * _MIX1
    x = x ^ (x >> np.uint64(27))
    x = x * _MIX2
    return x ^ (x >> np.uint64(31))


def _pow(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("up", ())) < n:
        size = max(n, SLICE_BYTES + 1)
        with np.errstate(over="ignore"):
            inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
            for name, base in (("up", _BASE), ("down", inverse)):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                _powers[name] = np.cumprod(steps, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def text_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets of n+1 rows) of a string column; a null row is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    places = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[places[0] : places[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, places - places[0]


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer row makes a range of its own."""
    n, row = len(offsets) - 1, 0
    while row < n:
        stop = int(np.searchsorted(offsets, offsets[row] + limit, "right")) - 1
        stop = min(n, max(stop, row + 1))
        yield row, stop
        row = stop


class Words:
    """The words of the rows in a slice: byte spans, row numbers and hashes."""

    def __init__(self, raw: np.ndarray, offsets: np.ndarray, lower: bool):
        offsets = offsets - offsets[0]
        if lower:
            raw = np.where((raw >= 65) & (raw <= 90), raw | 32, raw)
        self.raw, self.offsets, self.rows = raw, offsets, len(offsets) - 1
        n = len(raw)
        solid = (raw != 32) & ((raw < 9) | (raw > 13))
        opens, closes = solid.copy(), solid.copy()
        inner = offsets[1:-1]
        inner = inner[(inner > 0) & (inner < n)]
        if n:
            cut = np.zeros(n, bool)
            cut[inner] = True
            opens[1:] &= ~solid[:-1] | cut[1:]
            closes[:-1] &= ~solid[1:] | cut[1:]
        self.start = np.flatnonzero(opens)
        self.end = np.flatnonzero(closes) + 1
        #: words before each row, n+1 entries
        self.first = np.searchsorted(self.start, offsets)
        self.per_row = np.diff(self.first)
        self.row = np.repeat(np.arange(self.rows), self.per_row)

    def span_hash(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """64-bit hashes of byte spans; equal bytes give equal hashes wherever they stand."""
        if not len(start):
            return np.zeros(0, np.uint64)
        up, down = _pow(len(self.raw) + 1)
        with np.errstate(over="ignore"):
            if not hasattr(self, "_sums"):
                sums = np.empty(len(self.raw) + 1, np.uint64)
                sums[0] = 0
                np.cumsum((self.raw.astype(np.uint64) + np.uint64(1)) * up[: len(self.raw)], out=sums[1:])
                self._sums = sums
            value = (self._sums[end] - self._sums[start]) * down[start]
            return mix64(value + (end - start).astype(np.uint64) * _MIX2)

    def word_hash(self) -> np.ndarray:
        if not hasattr(self, "_hash"):
            self._hash = self.span_hash(self.start, self.end)
        return self._hash

    def windows(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(hash, first word) of every run of k words inside one row."""
        n = len(self.start) - k + 1
        if n <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        at = np.flatnonzero(self.row[:n] == self.row[k - 1 :])
        return combine([self.word_hash()[at + j] for j in range(k)]), at


def combine(parts: list[np.ndarray]) -> np.ndarray:
    """Order-sensitive hash of several hash columns."""
    with np.errstate(over="ignore"):
        total = np.full(len(parts[0]), np.uint64(len(parts)), np.uint64)
        for part in parts:
            total = (total ^ part) * _BASE + np.uint64(0x632BE59BD9B4E019)
            total ^= total >> np.uint64(29)
        return mix64(total)
