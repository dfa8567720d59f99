"""Vectorised word scanning over Arrow string arrays.

A word is a maximal run of bytes other than space and 0x09-0x0D; UTF-8 never uses those bytes inside a character, so work
on bytes equals work on code points. Hashes are polynomials over bytes (or over word hashes) taken from prefix sums modulo
2**64, then mixed; a whole chunk of documents is hashed by a fixed number of array passes.
"""

from __future__ import annotations

import sys
import types
from collections.abc import Callable, Iterator
from typing import TypeVar

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

T = TypeVar("T")


def kept_by_worker(key: str, make: Callable[[], T]) -> T:
    """A value that outlives the task: a worker process makes it once and later tasks in it find it again. Unlike a cache
    decorator, which travels to executors by name and so needs the repository there, this travels by value."""
    held = sys.modules.setdefault("linkwalk_kept", types.ModuleType("linkwalk_kept"))
    if not hasattr(held, key):
        setattr(held, key, make())
    return getattr(held, key)


SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_M1, _M2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(33))
    h = h * _M1
    h ^= h >> np.uint64(33)
    h *= _M2
    return h ^ (h >> np.uint64(33))


class Powers:
    """Powers of an odd base and of its inverse modulo 2**64, extended on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base | 1, pow(base | 1, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def to(self, n: int) -> None:
        if len(self.up) < n:
            size = max(n, 1 << 16)
            for name, b in (("up", self.base), ("down", self.inverse)):
                steps = np.full(size, b, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))


class Hasher:
    """Hashes words and runs of words; ``seed`` gives independent functions."""

    def __init__(self, seed: int = 1):
        r = np.random.default_rng(seed)
        draw = lambda *n: r.integers(1, 1 << 63, *n, dtype=np.uint64)
        self.values = draw(256)
        self.bytes, self.runs = Powers(int(draw(1)[0])), Powers(int(draw(1)[0]))

    def words(self, b: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        n = len(b)
        self.bytes.to(n + 1)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(self.values[b] * self.bytes.up[:n], out=sums[1:])
        return mix((sums[ends] - sums[starts]) * self.bytes.down[starts])

    def prefix(self, h: np.ndarray) -> np.ndarray:
        """Prefix sums from which :meth:`run` takes the hash of any run of words."""
        n = len(h)
        self.runs.to(n + 1)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(h * self.runs.up[:n], out=sums[1:])
        return sums

    def run(self, sums: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return mix((sums[hi] - sums[lo]) * self.runs.down[lo])


def texts(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n + 1 offsets of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    flat = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return (flat[offsets[0] : offsets[-1]], offsets - offsets[0]) if len(offsets) else (flat[:0], np.zeros(1, np.int64))


def chunks(offsets: np.ndarray, limit: int = 1 << 18) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` bytes; a longer document is a range of its own."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield lo, min(hi, n)
        lo = min(hi, n)


def find_words(b: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all words, and ``first[d]``: the index of document d's first word (n + 1 entries)."""
    inside = ~SEPARATOR[b]
    before = np.zeros(len(b), bool)
    before[1:] = inside[:-1]
    after = np.zeros(len(b), bool)
    after[:-1] = inside[1:]
    before[offsets[:-1][offsets[:-1] < len(b)]] = False
    after[offsets[1:][offsets[1:] > 0] - 1] = False
    starts = np.flatnonzero(inside & ~before)
    return starts, np.flatnonzero(inside & ~after) + 1, np.searchsorted(starts, offsets)
