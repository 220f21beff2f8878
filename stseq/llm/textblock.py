"""Whole batches of UTF-8 texts as NumPy arrays: words, word hashes and word-shingle hashes without a Python loop per word."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SPACES = np.zeros(256, bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Bytes of text that one block holds at most, unless a single text is longer.
BLOCK_BYTES = 1 << 18
_powers: dict[str, np.ndarray] = {}


def give_back() -> None:
    """Return freed memory to the system at the end of a task: workers wait for their next one with all that they hold."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # another C library
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def _power(n: int, base: int, name: str) -> np.ndarray:
    have = _powers.get(name)
    if have is None or len(have) < n + 1:
        seq = np.full(max(n, BLOCK_BYTES) + 1, np.uint64(base))
        seq[0] = 1
        made = np.cumprod(seq, dtype=np.uint64)
        if n > 4 * BLOCK_BYTES:
            return made
        have = _powers[name] = made
    return have


def mix(h: np.ndarray) -> np.ndarray:
    """64-bit finalizer."""
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def binary_arrays(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (one more than rows) of a binary column; null is empty."""
    column = column.cast(pa.large_binary()) if column.null_count == 0 else column.fill_null(b"").cast(pa.large_binary())
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = column.buffers()[2]
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), offsets


def blocks(column: pa.Array, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of rows (from, to, bytes, offsets from 0) of about ``size`` bytes each."""
    data, offsets = binary_arrays(column)
    at, n = 0, len(offsets) - 1
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + size, "right")) - 1
        to = min(max(to, at + 1), n)
        yield at, to, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        at = to


class Words:
    """Words (runs of bytes other than 0x20 and 0x09-0x0D) of the texts of one block, lower-cased in A-Z.

    ``starts``/``ends`` are byte positions, ``first`` has the index of each text's first word and one more.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, lower: bool = True):
        self.data = LOWER[data] if lower else data
        n = len(data)
        word = ~SPACES[data]
        edge = np.ones(n + 1, bool)
        edge[1:n] = ~word[:-1] if n else True
        edge[offsets] = True
        self.starts = np.flatnonzero(word & edge[:n])
        if n:
            after = np.ones(n, bool)
            after[:-1] = ~word[1:]
            after[offsets[(offsets > 0)] - 1] = True
            self.ends = np.flatnonzero(word & after) + 1
        else:
            self.ends = self.starts
        self.first = np.searchsorted(self.starts, offsets)

    def __len__(self) -> int:
        return len(self.starts)

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word's bytes."""
        n = len(self.data)
        up, down = _power(n, _BASE, "up"), _power(n, _INVERSE, "down")
        total = np.zeros(n + 1, np.uint64)
        np.cumsum(up[:n] * (self.data.astype(np.uint64) + np.uint64(1)), out=total[1:])
        h = (total[self.ends] - total[self.starts]) * down[self.starts]
        return mix(h + (self.ends - self.starts).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))

    def texts(self) -> np.ndarray:
        """Index of the text that each word belongs to."""
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def shingle_hashes(words: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word shingles of each text, repeats included, and the index of each text's first one.

    A text of fewer words than ``k``, but at least one, has the whole sequence as its only shingle.
    """
    n = np.diff(first)
    m = np.where(n == 0, 0, np.maximum(n - k + 1, 1))
    at = np.concatenate([[0], np.cumsum(m)])
    text = np.repeat(np.arange(len(n)), m)
    begin = first[:-1][text] + (np.arange(at[-1]) - at[:-1][text])
    end = first[1:][text]
    h = np.full(len(text), np.uint64(0x27D4EB2F165667C5))
    for j in range(k):
        pos = begin + j
        inside = pos < end
        w = words[np.minimum(pos, len(words) - 1)] if len(words) else np.zeros(0, np.uint64)
        h = np.where(inside, mix(h * np.uint64(0x9E3779B97F4A7C15) + w), h)
    return h, at


class Lookup:
    """Position of 64-bit hashes in a sorted array: one probe of a direct table, binary search for the few it cannot tell."""

    def __init__(self, keys: np.ndarray, bits: int = 21):
        self.keys, self.shift = keys, np.uint64(64 - bits)
        slot = (keys >> self.shift).astype(np.int64)
        first = np.concatenate([[True], slot[1:] != slot[:-1]]) if len(keys) else np.zeros(0, bool)
        self.table = np.full(1 << bits, -1, np.int32)
        self.table[slot[first]] = np.flatnonzero(first)
        self.crowded = np.bincount(slot, minlength=1 << bits) > 1

    def __call__(self, h: np.ndarray) -> np.ndarray:
        """Index, or -1."""
        if not len(self.keys):
            return np.full(len(h), -1, np.int64)
        slot = (h >> self.shift).astype(np.int64)
        at = self.table[slot].astype(np.int64)
        hit = (at >= 0) & (self.keys[at] == h)
        unsure = np.flatnonzero(~hit & self.crowded[slot])
        at[~hit] = -1
        if len(unsure):
            p = np.minimum(np.searchsorted(self.keys, h[unsure]), len(self.keys) - 1)
            at[unsure] = np.where(self.keys[p] == h[unsure], p, -1)
        return at
