"""Texts as arrays: words, hashes and rolling windows of whole Arrow batches, without a loop over documents.

Words are runs of bytes other than space and tab to carriage return. All hashes are polynomials over
64-bit words (wrapping), finished by a mixing step, so every window costs a subtraction and a product.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
CHUNK = 2 << 20
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix64(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U(33))
    h = h * U(0xFF51AFD7ED558CCD)
    h ^= h >> U(33)
    h *= U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U(33))


def powers(n: int, which: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i (mod 2^64) for i < n at least."""
    have = _powers.get(which)
    if have is None or len(have[0]) < n:
        size = max(n, 1 << 16)
        out = []
        for b in (_BASES[which], pow(_BASES[which], -1, 1 << 64)):
            a = np.full(size, b, U)
            a[0] = 1
            out.append(np.multiply.accumulate(a))
        have = _powers[which] = tuple(out)
    return have


def sums(values: np.ndarray, which: int) -> np.ndarray:
    """Prefix sums of values * base^i, with a leading 0."""
    out = np.zeros(len(values) + 1, U)
    np.cumsum(values * powers(len(values), which)[0][: len(values)], out=out[1:])
    return out


def windows(prefix: np.ndarray, at: np.ndarray, to: np.ndarray, which: int) -> np.ndarray:
    """Hashes of values[at:to] from their prefix sums; the length takes part."""
    return mix64((prefix[to] - prefix[at]) * powers(len(prefix), which)[1][at] + (to - at).astype(U) * U(0x9FB21C651E98DF25))


class Chunk:
    """Some rows of a batch: ``data`` their bytes end to end, ``off`` their offsets; ``rows`` their numbers in the batch."""

    def __init__(self, data: np.ndarray, off: np.ndarray, first: int):
        self.data, self.off, self.first, self.n = data, off, first, len(off) - 1

    def words(self, space: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of the words, and each row's first word (n + 1 numbers)."""
        d, off = self.data, self.off
        blank = space[d]
        cut = np.zeros(len(d) + 1, bool)
        cut[off] = True
        before = np.ones(len(d), bool)
        before[1:] = blank[:-1]
        after = np.ones(len(d), bool)
        after[:-1] = blank[1:]
        s = np.flatnonzero(~blank & (before | cut[:-1]))
        e = np.flatnonzero(~blank & (after | cut[1:])) + 1
        return s, e, np.searchsorted(s, off)

    def text(self, i: int) -> bytes:
        return self.data[self.off[i] : self.off[i + 1]].tobytes()


def chunks(column: pa.Array, limit: int = CHUNK) -> Iterator[Chunk]:
    """The rows of a string column, null as empty, in chunks of about ``limit`` bytes; a longer text is one of its own."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, o, d = column.buffers()
    off = np.frombuffer(o, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(d, np.uint8) if d is not None else np.zeros(0, np.uint8)
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, "right")) - 1)
        yield Chunk(data[off[i] : off[j]], off[i : j + 1] - off[i], i)
        i = j


def word_hashes(c: Chunk, s: np.ndarray, e: np.ndarray, which: int = 0) -> np.ndarray:
    return windows(sums(c.data.astype(U) + U(1), which), s, e, which)


def longs(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values of an integer column (0 for null) and which are not null."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    there = np.ones(len(column), bool) if not column.null_count else np.asarray(column.is_valid())
    return np.asarray(column.fill_null(0).cast(pa.int64()) if column.null_count else column.cast(pa.int64())), there
