"""Whole-batch text kernels on the UTF-8 bytes of an Arrow column, without a Python loop over words.

A word is a maximal run of bytes outside ``20`` and ``09``-``0D`` (hex); as UTF-8 never uses those
bytes inside a character, this is ``[^\\x20\\x09-\\x0D]+`` on code points. Words are named by a
64-bit polynomial hash over a table of random byte values, finished with a mixing step.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INVERSE = pow(_BASE, -1, 2**64)
BYTE_VALUES = np.random.Generator(np.random.PCG64(20240229)).integers(1, 2**63, 256, dtype=np.uint64) * _U(2) + _U(1)
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_POW: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**0..n-1 and their inverses, modulo 2**64."""
    if "up" not in _POW or len(_POW["up"]) < n:
        size = max(n, 1 << 21)
        _POW["up"], _POW["down"] = _powers(_BASE, size), _powers(_BASE_INVERSE, size)
    return _POW["up"][:n], _POW["down"][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (the finalizer of splitmix64)."""
    h = (h ^ (h >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


def pieces(column: pa.Array, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` bytes of text at most, one row at least."""
    lengths = np.diff(offsets(column))
    at, n = 0, len(lengths)
    total = np.concatenate([[0], np.cumsum(lengths)])
    while at < n:
        end = max(at + 1, int(np.searchsorted(total, total[at] + most, "right")) - 1)
        yield at, min(end, n)
        at = min(end, n)


def offsets(column: pa.Array) -> np.ndarray:
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    buf = column.buffers()[1]
    if buf is None:
        return np.zeros(len(column) + 1, np.int64)
    return np.frombuffer(buf, kind, len(column) + 1 + column.offset)[column.offset :].astype(np.int64)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the bounds of its rows in them (nulls are empty)."""
    off = offsets(column)
    buf = column.buffers()[2]
    data = np.frombuffer(buf, np.uint8) if buf is not None and buf.size else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


class Words:
    """start, end: byte bounds of the words in ``data``; row_at: word bounds of the rows; hash: 64-bit names."""

    def __init__(self, column: pa.Array, lower: bool = False):
        self.data, self.bounds = text_bytes(column)
        data, n = self.data, len(self.data)
        solid = np.empty(n + 2, bool)
        solid[0] = solid[-1] = False
        np.logical_not(SPACE[data], out=solid[1:-1])
        first = solid[1:] & ~solid[:-1]
        last = solid[:-1] & ~solid[1:]
        cut = self.bounds[1:-1]
        cut = cut[(cut > 0) & (cut < n)]
        both = cut[solid[cut] & solid[cut + 1]]  # a row ends inside what looks like one word
        first[both] = True
        last[both] = True
        self.start, self.end = np.flatnonzero(first[:-1] if n else first[:0]), np.flatnonzero(last[: n + 1])
        if n == 0:
            self.start = self.end = np.zeros(0, np.int64)
        self.row_at = np.searchsorted(self.start, self.bounds)
        if lower:
            low = data.copy()
            low[(low >= 65) & (low <= 90)] += 32
            self.data = data = low
        up, down = powers(n + 1)
        total = np.empty(n + 1, np.uint64)
        total[0] = 0
        np.cumsum(BYTE_VALUES[data] * up[:n], out=total[1:])
        self.hash = mix((total[self.end] - total[self.start]) * down[self.start] + (self.end - self.start).astype(np.uint64))

    def rows(self) -> np.ndarray:
        """The row of each word."""
        return np.repeat(np.arange(len(self.row_at) - 1), np.diff(self.row_at))


def windows(h: np.ndarray, k: int) -> np.ndarray:
    """64-bit names of all runs of k consecutive words (the caller drops those that cross rows)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    up, down = powers(len(h) + 1)
    total = np.empty(len(h) + 1, np.uint64)
    total[0] = 0
    np.cumsum(h * up[: len(h)], out=total[1:])
    return mix((total[k:] - total[:-k]) * down[:n])
