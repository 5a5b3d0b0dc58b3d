"""Vectorised words and word-sequence hashes over the UTF-8 buffers of Arrow batches.

A word is a maximal run of bytes other than space and 0x09-0x0D, as the contracts define it. Every function works on a
*chunk*: some whole documents in one contiguous buffer. A word's 64-bit hash is a polynomial over a table of random byte
values, taken from one running sum over the buffer and then mixed, so that no Python code runs for each word.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 1 << 19
_BASE = 0x9E3779B97F4A7C15
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_TABLE = np.random.default_rng(20).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values whose every output bit depends on every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def powers(n: int, base: int = _BASE) -> tuple[np.ndarray, np.ndarray]:
    """base**i and its inverse modulo 2**64 for i up to n; kept up to a few chunks' length."""
    up, down = _powers.get(base, (np.ones(0, np.uint64),) * 2)
    if len(up) < n:
        size = n + n // 8 + 1024
        up, down = (np.full(size, v, np.uint64) for v in (base, pow(base, -1, 2**64)))
        up[0] = down[0] = 1
        np.multiply.accumulate(up, out=up)
        np.multiply.accumulate(down, out=down)
        if size <= 2 * CHUNK_BYTES:
            _powers[base] = up, down
    return up[:n], down[:n]


def sums(values: np.ndarray, base: int = _BASE) -> tuple[np.ndarray, np.ndarray]:
    """Running polynomial sums with a leading 0, and the inverse powers that move a range to position 0."""
    up, down = powers(len(values) + 1, base)
    total = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * up[:-1], out=total[1:])
    return total, down


@dataclass
class Words:
    """The words of one chunk: byte ranges, hashes, and the first word of each document (one entry more than documents)."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    hashes: np.ndarray
    first: np.ndarray

    def windows(self, size: int, base: int = 0xD6E8FEB86659FD93) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all word windows of this size, and the first word of each; none spans two documents. Another odd base gives independent hashes."""
        n = len(self.hashes) - size + 1
        if n <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        total, down = sums(self.hashes, base)
        at = np.arange(n)
        left = np.repeat(self.first[1:], np.diff(self.first))[:n] - at
        at = at[left >= size]
        return mix((total[at + size] - total[at]) * down[at] + np.uint64(size)), at


def words(data: np.ndarray, bounds: np.ndarray, lower: bool = False) -> Words:
    """data: the bytes of the documents; bounds: where each begins, and the end."""
    if lower:
        data = _LOWER[data]
    n = len(data)
    inside = np.zeros(n + 2, bool)
    np.logical_not(_SPACE[data], out=inside[1:-1])
    cut = np.zeros(n + 1, bool)
    cut[bounds] = True
    starts = np.flatnonzero(inside[1:-1] & (~inside[:-2] | cut[:-1]))
    ends = np.flatnonzero(inside[1:-1] & (~inside[2:] | cut[1:])) + 1
    total, down = sums(_TABLE[data])
    hashes = mix((total[ends] - total[starts]) * down[starts] ^ (ends - starts).astype(np.uint64) * np.uint64(0xA24BAED4963EE407))
    return Words(data, starts, ends, hashes, np.searchsorted(starts, bounds))


def chunks(column: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from row, to row, bytes, bounds) of runs of whole documents with up to `limit` bytes, or one longer document. A null has no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    n = len(column)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    body = column.buffers()[2]
    data = np.frombuffer(body, np.uint8) if body is not None and body.size else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield at, to, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        at = to
