"""Vectorised word tables over Arrow string columns.

A piece is a run of whole documents of bounded bytes (one giant document may
stand alone). Words are found and hashed with prefix sums over the piece's UTF-8
bytes, so no Python object exists per word.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: ASCII upper to lower case; other bytes stand for themselves.
LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
#: Word separators: space, and tab to carriage return (what bytes.split() uses).
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_LOWER = np.frombuffer(LOWER, np.uint8)

_BASE = np.uint64(0x9E3779B97F4A7C15)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words with good avalanche."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _ladder(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n-1 of the odd base modulo 2^64, and of its inverse."""
    size = 1 << max(16, int(n - 1).bit_length())
    if size not in _powers:
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        up, down = np.full(size, _BASE), np.full(size, inverse)
        up[0] = down[0] = 1
        if size > 1 << 22:  # a giant document: used once, not kept
            return np.multiply.accumulate(up), np.multiply.accumulate(down)
        _powers[size] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _powers[size]


def span_hashes(values: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of values[start:end] for each span, by one prefix sum."""
    up, down = _ladder(len(values) + 1)
    total = np.empty(len(values) + 1, np.uint64)
    total[0] = 0
    np.cumsum(values * up[: len(values)], out=total[1:])
    return mix64((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


@dataclass
class Words:
    """Words of a piece: hash, first and past-the-end byte; first[i]:first[i+1] are row i's words."""

    row: int
    rows: int
    raw: np.ndarray
    offsets: np.ndarray
    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def windows(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all windows of k consecutive words of one row; first window of each row."""
        n = np.maximum(self.counts() - k + 1, 0)
        first = np.concatenate(([0], np.cumsum(n)))
        at = np.arange(first[-1]) + np.repeat(self.first[:-1] - first[:-1], n)
        return span_hashes(self.hash, at, at + k), first


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column, "").cast(pa.large_string())
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def pieces(column: pa.Array, most: int = 1 << 20) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) of runs of whole rows of about ``most`` bytes."""
    raw, offsets = text_buffers(column)
    row, n = 0, len(offsets) - 1
    while row < n:
        to = max(row + 1, int(np.searchsorted(offsets, offsets[row] + most, "right")) - 1)
        yield row, raw[offsets[row] : offsets[to]], offsets[row : to + 1] - offsets[row]
        row = to


def words(column: pa.Array, lower: bool, most: int = 1 << 20) -> Iterator[Words]:
    """Word tables of a string column, piece by piece."""
    for row, raw, offsets in pieces(column, most):
        raw = _LOWER[raw] if lower else raw
        inside = ~_SPACE[raw]
        edge = np.zeros(len(raw) + 1, bool)
        edge[offsets] = True
        before = np.empty(len(raw), bool)
        before[:1] = False
        before[1:] = inside[:-1]
        start = np.flatnonzero(inside & (~before | edge[:-1]))
        after = np.empty(len(raw), bool)
        after[-1:] = False
        after[:-1] = inside[1:]
        end = np.flatnonzero(inside & (~after | edge[1:])) + 1
        yield Words(row, len(offsets) - 1, raw, offsets, span_hashes(raw.astype(np.uint64) + np.uint64(1), start, end), start, end, np.searchsorted(start, offsets))


def ragged(values: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """values[start:start + size] of all spans, end to end."""
    ends = np.cumsum(size)
    return values[np.arange(ends[-1] if len(ends) else 0) + np.repeat(start - (ends - size), size)]


class HashTable:
    """Places of 64-bit keys by open addressing, looked up for whole arrays. At most half of its slots are filled."""

    def __init__(self, bits: int):
        self.shift, self.mask, self.most = np.uint64(64 - bits), (1 << bits) - 1, 1 << (bits - 1)
        self.clear()

    def clear(self) -> None:
        self.keys, self.place, self.size = np.zeros(self.mask + 1, np.uint64), np.full(self.mask + 1, -1, np.int32), 0

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Places of keys, -1 for those not there."""
        slot = (keys >> self.shift).astype(np.int64)
        out = np.where(self.keys[slot] == keys, self.place[slot], -1)
        open_ = np.flatnonzero((out < 0) & (self.place[slot] >= 0))
        slot = slot[open_]
        while len(open_):
            slot = (slot + 1) & self.mask
            here = self.place[slot]
            hit = (self.keys[slot] == keys[open_]) & (here >= 0)
            out[open_[hit]] = here[hit]
            more = ~hit & (here >= 0)
            open_, slot = open_[more], slot[more]
        return out

    def add(self, keys: np.ndarray, places: np.ndarray) -> None:
        """Distinct keys that are not there yet; there must be room."""
        slot, at = (keys >> self.shift).astype(np.int64), np.arange(len(keys))
        self.size += len(keys)
        while len(at):
            free = np.flatnonzero(self.place[slot] < 0)
            first = free[np.unique(slot[free], return_index=True)[1]]
            self.keys[slot[first]], self.place[slot[first]] = keys[at[first]], places[at[first]]
            left = np.ones(len(at), bool)
            left[first] = False
            at, slot = at[left], (slot[left] + 1) & self.mask


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run, which gives freed memory back when it ends: a worker waits for its next task with what it needs only."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):  # not every C library can
            ctypes.CDLL(None).malloc_trim(0)

    return whole


def row_texts(column: pa.Array, lower: bool = False) -> Iterator[bytes]:
    """Each row's text as UTF-8, A-Z lowered if asked; null as empty."""
    raw, offsets = text_buffers(column)
    raw = raw.tobytes()
    for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
        yield raw[a:b].translate(LOWER) if lower else raw[a:b]
