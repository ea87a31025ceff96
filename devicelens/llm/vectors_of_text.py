"""Whole-batch hashing of words with numpy: the texts of a batch are one array of bytes, and no Python code runs for a word.

Words are runs of bytes that are no ASCII white space, after lower-casing A to Z. A word's hash is a polynomial in its bytes modulo
2**64, got from prefix sums, and then mixed with the word's length.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_P = np.uint64(0x9E3779B97F4A7C15 | 1)
_P_INVERSE = np.uint64(pow(int(_P), -1, 1 << 64))
_LONGEST = 1 << 18  # bytes for which powers are kept; longer texts are hashed in pieces
_RANDOM = np.random.default_rng(20240607).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_VALUE = _RANDOM[_LOWER]
_powers: list[np.ndarray] = []


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of the multiplier and of its inverse."""
    if not _powers:
        with np.errstate(over="ignore"):
            for base in (_P, _P_INVERSE):
                x = np.full(_LONGEST + 1, base, np.uint64)
                x[0] = 1
                _powers.append(np.multiply.accumulate(x))
    return _powers[0], _powers[1]


def word_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where words begin and end."""
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = ~_SPACE[data]
    step = np.diff(inside)
    return np.flatnonzero(step == 1), np.flatnonzero(step == -1)


def hashed_words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """64-bit hash, begin and end of every word."""
    begin, end = word_bounds(data)
    hashes = np.empty(len(begin), np.uint64)
    power, inverse = powers()
    i = 0
    while i < len(begin):
        low = begin[i]
        j = int(np.searchsorted(end, low + _LONGEST, "right"))
        if j <= i:  # a word longer than the powers reach: piece by piece
            x = np.zeros(1, np.uint64)
            for at in range(int(low), int(end[i]), _LONGEST):
                part = _VALUE[data[at : min(at + _LONGEST, int(end[i]))]]
                x = mixed(x + np.sum(part * power[: len(part)], dtype=np.uint64))
            hashes[i], i = x[0], i + 1
            continue
        span = data[low : end[j - 1]]
        sums = np.zeros(len(span) + 1, np.uint64)
        np.cumsum(_VALUE[span] * power[: len(span)], out=sums[1:])
        b, e = begin[i:j] - low, end[i:j] - low
        hashes[i:j] = (sums[e] - sums[b]) * inverse[b]
        i = j
    return mixed(hashes + (end - begin).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), begin, end


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The texts in one array, a line end after each, and where each begins (one more entry than texts)."""
    starts = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=starts[1:])
    return np.frombuffer(b"\n".join([*texts, b""]), np.uint8), starts


def batches_of(texts: list[bytes], at_most: int = 1 << 19) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about at_most bytes together."""
    first, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > at_most:
            yield first, i
            first, size = i, 0
        size += len(t)
    if first < len(texts):
        yield first, len(texts)


def words_by_text(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words, and the index of the first word of each text (one more entry than texts)."""
    if not texts:
        return np.empty(0, np.uint64), np.zeros(1, np.int64)
    found, firsts, n = [], [], 0
    for a, b in batches_of(texts):
        data, starts = joined(texts[a:b])
        hashes, begin, _ = hashed_words(data)
        firsts.append(np.searchsorted(begin, starts[:-1]) + n)
        found.append(hashes)
        n += len(hashes)
    return np.concatenate(found), np.concatenate([*firsts, [n]]).astype(np.int64)
