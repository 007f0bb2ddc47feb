"""NumPy text kernels shared by the corpus operators.

A *word* is a maximal run of characters other than space and the controls
TAB..CR, the definition every word count and shingle here uses.  All kernels
work on whole texts; long ones are hashed in pieces of bounded size.
"""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_PIECE = 1 << 21

WHITESPACE = np.zeros(256, dtype=bool)
WHITESPACE[[9, 10, 11, 12, 13, 32]] = True

_powers = np.ones(1, dtype=np.uint64)


def _power_table(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        size = max(n, 64)
        base = np.full(size, _BASE, dtype=np.uint64)
        base[0] = 1
        _powers = np.cumprod(base, dtype=np.uint64)
    return _powers


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of the splitmix generator, elementwise on uint64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte offsets [start, end) of the words of a UTF-8 byte array."""
    if not len(data):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    inside = np.zeros(len(data) + 2, dtype=np.int8)
    inside[1:-1] = ~WHITESPACE[data]
    step = np.diff(inside)
    return np.flatnonzero(step == 1), np.flatnonzero(step == -1)


def hash_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, second: bool = False):
    """64-bit hash of each word; words are hashed in pieces of about 2 MB.

    ``second`` also returns an independent hash, for 128 bits in all.
    """
    out = np.empty(len(starts), dtype=np.uint64)
    more = np.empty(len(starts) if second else 0, dtype=np.uint64)
    lo = 0
    while lo < len(starts):
        hi = max(lo + 1, int(np.searchsorted(ends, starts[lo] + _PIECE, side="right")))
        s, e = starts[lo:hi], ends[lo:hi]
        length = e - s
        first = np.concatenate(([0], np.cumsum(length)[:-1]))
        total = int(length.sum())
        within = np.arange(total, dtype=np.int64) - np.repeat(first, length)
        chars = data[np.repeat(s, length) + within].astype(np.uint64) + np.uint64(1)
        power = _power_table(int(length.max()))[within]
        if second:
            more[lo:hi] = np.add.reduceat((chars + np.uint64(0xD6E8FEB86659FD93)) * (power ^ (power >> np.uint64(31))), first)
        chars *= power
        out[lo:hi] = np.add.reduceat(chars, first) + length.astype(np.uint64)
        lo = hi
    return (mix64(out), mix64(more)) if second else mix64(out)


def text_words(text: str | None) -> np.ndarray:
    """Hashes of the words of a text, in order (null counts as empty)."""
    data = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), dtype=np.uint8)
    return hash_words(data, *word_bounds(data))


def ngram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Order-sensitive hashes of the word n-grams (none if fewer than n words)."""
    m = len(words) - n + 1
    if m <= 0:
        return np.empty(0, dtype=np.uint64)
    acc = np.zeros(m, dtype=np.uint64)
    for i in range(n):
        acc = acc * np.uint64(_BASE) + words[i : i + m]
    return mix64(acc)


def shingle_set(words: np.ndarray, n: int = 5) -> np.ndarray:
    """Sorted distinct n-word shingles; a text of 1..n-1 words is one shingle."""
    if not len(words):
        return np.empty(0, dtype=np.uint64)
    return np.unique(ngram_hashes(words, min(n, len(words))))


def minimizers(grams: np.ndarray, window: int) -> np.ndarray:
    """Positions of the window minima of a hash sequence (ties: the first).

    Any run of ``window`` consecutive grams contains one of them, so equal runs
    of that many grams share a position with an equal gram.
    """
    n = len(grams)
    if n == 0:
        return np.empty(0, np.int64)
    if n <= window:
        return np.array([int(np.argmin(grams))])
    view = np.lib.stride_tricks.sliding_window_view(grams, window)
    return np.unique(np.argmin(view, axis=1) + np.arange(n - window + 1))


def char_offsets(data: np.ndarray) -> np.ndarray:
    """Code points before each byte offset, length len(data)+1."""
    lead = np.zeros(len(data) + 1, dtype=np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=lead[1:])
    return lead
