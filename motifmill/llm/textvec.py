"""Vectorised text primitives over Arrow buffers, shared by the document operators.

Every function works on the UTF-8 bytes of many texts at once, so that no Python
string or per-word loop is needed.  Texts are handed out in pieces of bounded size:
a piece holds whole texts, as many as fit, or one text that is longer by itself.
Word rule: maximal runs of bytes other than space and 0x09-0x0D.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

PIECE_BYTES = 2 << 20

_rng = np.random.default_rng(20240229)
_BYTE64 = _rng.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_SPACES = [0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]
IS_SPACE = np.zeros(256, bool)
IS_SPACE[_SPACES] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_BASE_INV = pow(int(_BASE), -1, 2**64)
_tables = {"up": _powers(int(_BASE), 1 << 16), "down": _powers(_BASE_INV, 1 << 16)}


def _table(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_tables["up"]) < n:
        size = 1 << int(n - 1).bit_length()
        _tables["up"], _tables["down"] = _powers(int(_BASE), size), _powers(_BASE_INV, size)
    return _tables["up"], _tables["down"]


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; nulls become empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_null(column.type):
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offs, data = column.buffers()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(offs, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def pieces(offsets: np.ndarray, most: int = PIECE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts together have at most `most` bytes (or are one text)."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + most, "right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi
        lo = hi


class Words:
    """Words of several texts: byte ranges, and the word range of each text."""

    __slots__ = ("data", "starts", "ends", "first")

    def __init__(self, data: np.ndarray, offsets: np.ndarray, lower: bool = False):
        """offsets: of the texts in data, from 0."""
        self.data = LOWER[data] if lower else data
        n = len(data)
        inside = ~IS_SPACE[data]
        begin = inside.copy()
        begin[1:] &= ~inside[:-1]
        cut = offsets[(offsets < n) & (offsets >= 0)]
        begin[cut] = inside[cut]
        close = inside.copy()
        close[:-1] &= ~inside[1:]
        before = cut[cut > 0] - 1
        close[before] = inside[before]
        self.starts, self.ends = np.flatnonzero(begin), np.flatnonzero(close) + 1
        self.first = np.searchsorted(self.starts, offsets)

    def __len__(self) -> int:
        return len(self.starts)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts())

    def hashes(self) -> np.ndarray:
        """64-bit value of each word, the same wherever the word stands."""
        out = np.empty(len(self), np.uint64)
        lo = 0
        while lo < len(self):
            hi = int(np.searchsorted(self.ends, self.starts[lo] + (1 << 16), "right"))
            hi = max(hi, lo + 1)
            s0, e0 = self.starts[lo], self.ends[hi - 1]
            up, down = _table(int(e0 - s0) + 1)
            sums = np.zeros(e0 - s0 + 1, np.uint64)
            np.cumsum(_BYTE64[self.data[s0:e0]] * up[: e0 - s0], out=sums[1:])
            s, e = self.starts[lo:hi] - s0, self.ends[lo:hi] - s0
            out[lo:hi] = mix((sums[e] - sums[s]) * down[s])
            lo = hi
        return out

    def grams(self, hashes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(values, positions) of the k-word sequences that lie within one text."""
        m = len(hashes) - k + 1
        if m <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        value = hashes[:m].copy()
        for j in range(1, k):
            value *= np.uint64(0x9FB21C651E98DF25)
            value += hashes[j : j + m]
        ok = np.ones(m, bool)
        for j in range(1, k):
            at = self.first[1:-1] - j
            ok[at[(at >= 0) & (at < m)]] = False
        at = np.flatnonzero(ok)
        return mix(value[at]), at


def crc32_of_ids(ids) -> np.ndarray:
    """crc32 of each id's decimal text."""
    import zlib

    return np.fromiter((zlib.crc32(str(i).encode()) if i is not None else 0 for i in ids), np.int64, len(ids))
