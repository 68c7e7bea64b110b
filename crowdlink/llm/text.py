"""Words of whole texts as numbers, by whole Arrow batches at a time."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: Fixed byte classes: A-Z are lowered; words are runs of 0-9, a-z and all bytes of non-ASCII characters.
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_WORD = np.zeros(256, bool)
_WORD[48:58] = _WORD[97:123] = _WORD[128:] = True
_BASE = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values whose bits all depend on each other."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def flat_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The texts' UTF-8 bytes end to end, and where each starts; a null text is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = column.buffers()[2] if len(column) else None
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, offsets - offsets[0]


def word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each lower-cased word, and the first word's index of each text (one more at the end)."""
    raw, offsets = flat_bytes(column)
    if not raw.size:
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    low = _LOWER[raw]
    inside = _WORD[low]
    fresh = inside.copy()
    fresh[1:] &= ~inside[:-1]
    heads = offsets[:-1][offsets[:-1] < raw.size]
    fresh[heads] = inside[heads]  # a text never continues the word before it
    starts = np.flatnonzero(fresh)
    if not starts.size:
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    at = np.flatnonzero(inside)
    first = np.searchsorted(at, starts)
    size = np.diff(np.append(first, at.size))
    place = np.arange(at.size) - np.repeat(first, size)
    with np.errstate(over="ignore"):
        powers = np.full(int(size.max()) + 1, _BASE)
        powers[0] = 1
        powers = np.multiply.accumulate(powers)
        sums = np.add.reduceat((low[at].astype(np.uint64) + np.uint64(1)) * powers[place], first)
        hashes = mix(sums ^ (size.astype(np.uint64) << np.uint64(48)))
    return hashes, np.searchsorted(starts, offsets).astype(np.int64)


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each window of ``width`` words and its text's index; a text of fewer words, but not none, is one window."""
    counts = np.diff(bounds)
    windows = np.where(counts >= width, counts - width + 1, (counts > 0).astype(np.int64))
    owner = np.repeat(np.arange(len(counts)), windows)
    if not owner.size:
        return np.zeros(0, np.uint64), owner
    place = np.arange(owner.size) - np.repeat(np.cumsum(windows) - windows, windows)
    start, length = bounds[:-1][owner] + place, np.minimum(counts[owner], width)
    out = np.zeros(owner.size, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(width):
            here = length > k
            out[here] = mix(out[here] * np.uint64(0xD6E8FEB86659FD93) + words[start[here] + k] + np.uint64(k + 1))
    return out, owner
