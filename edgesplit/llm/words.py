"""Words of many texts at once, straight from Arrow's string buffers.

A word is a run of bytes outside ``\\x20 \\x09-\\x0D``; bytes of multi-byte characters are never
blanks, so whole UTF-8 buffers can be split with array operations.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_draw = np.random.default_rng(20_260)
_BYTE_VALUES = _draw.integers(1, 1 << 63, (2, 256), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASES = [int(x) * 8 + 5 for x in _draw.integers(1 << 40, 1 << 60, 2)]
_STEPS = _draw.integers(1, 1 << 63, (2, 64), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


@dataclass
class Words:
    """Bytes of all texts, where each word begins and ends in them, and each text's first word."""

    data: np.ndarray
    begins: np.ndarray
    ends: np.ndarray
    first: np.ndarray  # one more entry than texts

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def split(texts: pa.Array) -> Words:
    """Words of a string array; a null has none."""
    if texts.null_count:
        texts = texts.fill_null("")
    texts = texts.cast(pa.large_string())
    n = len(texts)
    if not n:
        empty = np.zeros(0, np.int64)
        return Words(np.zeros(0, np.uint8), empty, empty, np.zeros(1, np.int64))
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    low, high = int(offsets[0]), int(offsets[-1])
    buffer = texts.buffers()[2]
    data = np.frombuffer(buffer, np.uint8)[low:high] if buffer is not None and high > low else np.zeros(0, np.uint8)
    bounds = offsets - low
    inside = ~_BLANK[data]
    # A text's last word ends with it, even if the next text begins without a blank.
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    ends = inside.copy()
    ends[:-1] &= ~inside[1:]
    edges = bounds[:-1][(np.diff(bounds) > 0)]
    begins[edges] |= inside[edges]
    edges = edges[edges > 0]
    ends[edges - 1] |= inside[edges - 1]
    begins, ends = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return Words(data, begins, ends, np.searchsorted(begins, bounds))


def _powers(base: int, n: int) -> np.ndarray:
    steps = np.full(max(1, n), base, np.uint64)
    steps[0] = 1
    return np.multiply.accumulate(steps)


_cache: dict[tuple[int, bool], np.ndarray] = {}


def _power_table(which: int, inverse: bool, n: int) -> np.ndarray:
    known = _cache.get((which, inverse))
    if known is None or len(known) < n:
        base = pow(_BASES[which], -1, 1 << 64) if inverse else _BASES[which]
        known = _cache[which, inverse] = _powers(base, max(n, 1 << 16))
    return known[:n]


def hashes(words: Words, which: int = 0) -> np.ndarray:
    """A 64-bit hash of each word's bytes; ``which`` picks one of two independent hashes."""
    n = len(words.data)
    running = np.zeros(n + 1, np.uint64)
    np.cumsum(_BYTE_VALUES[which][words.data] * _power_table(which, False, n), dtype=np.uint64, out=running[1:])
    out = (running[words.ends] - running[words.begins]) * _power_table(which, True, n + 1)[words.begins]
    return mix(out)


def mix(x: np.ndarray) -> np.ndarray:
    """Spread a 64-bit value over all its bits."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def window_hashes(word_hashes: np.ndarray, size: int, which: int = 0) -> np.ndarray:
    """Hash of the ``size`` words that begin at each position; the last size-1 positions have none."""
    n = len(word_hashes) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = word_hashes[:n] * _STEPS[which, 0]
    for i in range(1, size):
        out += word_hashes[i : n + i] * _STEPS[which, i % 64]
    return mix(out)


def normalised(words: Words, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes with one blank after each word, and where each word begins and ends in them."""
    data = words.data
    if lower:
        data = np.where((data >= 65) & (data <= 90), data + np.uint8(32), data)
    sizes = words.ends - words.begins
    begins = np.concatenate(([0], np.cumsum(sizes + 1)))[:-1] if len(sizes) else np.zeros(0, np.int64)
    out = np.full(int((sizes + 1).sum()), 32, np.uint8)
    keep = ~_BLANK[words.data]
    places = np.arange(int(sizes.sum())) + np.repeat(np.arange(len(sizes)), sizes)
    out[places] = data[keep]
    return out, begins, begins + sizes


def documents(batch_texts: pa.Array, bytes_at_once: int):
    """Ranges of consecutive texts of about so many bytes together: ``(start, stop)``; one text at least."""
    n = len(batch_texts)
    sizes = np.asarray(pc.binary_length(batch_texts).fill_null(0)) if n else np.zeros(0, np.int64)
    at = 0
    while at < n:
        end, total = at, 0
        while end < n and (end == at or total + sizes[end] <= bytes_at_once):
            total += int(sizes[end])
            end += 1
        yield at, end
        at = end
