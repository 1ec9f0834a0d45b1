"""Vectorised text primitives: whole Arrow batches as byte buffers, words and hashes by NumPy.

A hash of a byte range is a difference of prefix sums of ``byte * R**position`` modulo 2**64, moved
back to position 0 by the inverse power, so each of all ranges costs a few array operations.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

R = np.uint64(0x9E3779B97F4A7C15 | 1)
R_INV = np.uint64(pow(int(R), -1, 1 << 64))
_POWERS: list[np.ndarray] = []

SPACE = np.zeros(256, dtype=bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
#: separators where a word is a run of letters (any byte of a non-ASCII character counts as letter)
NOT_LETTER = np.ones(256, dtype=bool)
NOT_LETTER[65:91] = NOT_LETTER[97:123] = NOT_LETTER[128:] = False
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of an Arrow string array and its n+1 offsets; null counts as empty."""
    flat = pc.fill_null(texts, "").cast(pa.large_string())
    if isinstance(flat, pa.ChunkedArray):
        flat = flat.combine_chunks()
    _, offs, data = flat.buffers()
    offsets = np.frombuffer(offs, dtype=np.int64, count=len(flat) + 1 + flat.offset)[flat.offset:]
    base = int(offsets[0])
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[base : int(offsets[-1])], offsets - base


def give_back() -> None:
    """Return freed memory to the system: an idle worker should not hold what its last task needed."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``limit`` text bytes (at least one row each)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            floor = int(size[at - 1]) if at else 0
            to = max(at + 1, int(np.searchsorted(size, floor + limit, "right")))
            yield batch.slice(at, to - at)
            at = to
        del batch, size
        give_back()


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """R**i and R**-i for i up to n; the longest tables so far are kept."""
    if len(_POWERS) == 0 or len(_POWERS[0]) <= n:
        up, down = np.full(n + 1, R), np.full(n + 1, R_INV)
        up[0] = down[0] = 1
        _POWERS[:] = [np.multiply.accumulate(up), np.multiply.accumulate(down)]
    return _POWERS[0], _POWERS[1]


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over all 64."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def prefix(values: np.ndarray, seed: int = 0) -> np.ndarray:
    """Prefix sums for :func:`ranges`; another seed gives each byte another 64-bit value."""
    if seed:
        values = np.random.default_rng(seed).integers(0, 1 << 64, 256, dtype=np.uint64)[values]
    out = np.zeros(len(values) + 1, dtype=np.uint64)
    np.cumsum((values.astype(np.uint64) + np.uint64(1)) * powers(len(values))[0][: len(values)], out=out[1:])
    return out


def ranges(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Mixed hashes of the ranges [start, end)."""
    return mix((sums[ends] - sums[starts]) * powers(len(sums))[1][starts] + (ends - starts).astype(np.uint64))


def tokens(data: np.ndarray, offsets: np.ndarray, separators: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and the index of the first word of each text (n+1 entries)."""
    word = ~separators[data]
    edge = np.zeros(len(data) + 1, dtype=bool)
    edge[offsets] = True
    before = np.zeros(len(data), dtype=bool)
    if len(data):
        before[1:] = word[:-1]
    starts = np.flatnonzero(word & (~before | edge[:-1]))
    after = np.zeros(len(data), dtype=bool)
    if len(data):
        after[:-1] = word[1:]
    ends = np.flatnonzero(word & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def owners(first: np.ndarray) -> np.ndarray:
    """For each item the text that holds it."""
    return np.repeat(np.arange(len(first) - 1), np.diff(first))
