"""An enhanced suffix array (order and common prefixes) over a set of byte strings, and the interval scan that finds maximal repeats."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_STEPS = (8, 16, 32, 64, 128)
DEPTH = 2 * _STEPS[-1]  # bytes that order suffixes; longer common prefixes count as this long


class EnhancedSuffixArray:
    """Suffixes of all strings in order, told apart on their first 256 bytes; none reaches beyond its string's end.

    Built by doubling: ranks by 8 bytes, then by 16, 32, 64, 128; the last order is by 256.
    """

    def __init__(self, strings: list[bytes]):
        lengths = np.array([len(s) for s in strings], np.int64)
        self.data = np.frombuffer(b"".join(strings), np.uint8)
        n = len(self.data)
        self.first = np.concatenate([[0], np.cumsum(lengths)])
        self.string = np.repeat(np.arange(len(strings), dtype=np.int32), lengths)
        self.room = (self.first[1:][self.string] - np.arange(n)).astype(np.int32)  # bytes up to the string's end
        key = np.zeros(n, np.uint64)
        for k in range(8):  # bytes beyond the end count as nothing; how much room there is tells them from zeros
            inside = np.flatnonzero(self.room > k)
            key[inside] |= self.data[inside + k].astype(np.uint64) << np.uint64(56 - 8 * k)
        self.ranks: list[np.ndarray] = []
        order = np.lexsort((np.minimum(self.room, 8), key))
        rank = self._ranked(order, key, np.minimum(self.room, 8))
        self.ranks.append(rank)
        for step in _STEPS:
            behind = np.zeros(n, np.int64)
            inside = np.flatnonzero(self.room > step)
            behind[inside] = rank[inside + step] + 1
            behind += rank.astype(np.int64) * (n + 1)
            order = np.argsort(behind)
            rank = self._ranked(order, behind)
            if step != _STEPS[-1]:
                self.ranks.append(rank)
        self.order = order

    @staticmethod
    def _ranked(order: np.ndarray, *keys: np.ndarray) -> np.ndarray:
        rank = np.zeros(len(order), np.int32)
        new = np.zeros(len(order), bool)
        for key in keys:
            new[1:] |= key[order[1:]] != key[order[:-1]]
        rank[order] = np.cumsum(new)
        return rank

    def common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Length of the common prefix of the suffixes at a and at b."""
        limit = np.minimum(self.room[a], self.room[b])
        length = np.zeros(len(a), np.int64)
        going = np.arange(len(a))
        while len(going):  # whole 128s, as long as they agree
            at = length[going]
            fits = limit[going] - at >= 128
            going, at = going[fits], at[fits]
            same = self.ranks[4][a[going] + at] == self.ranks[4][b[going] + at]
            going = going[same]
            length[going] += 128
        for level, step in ((3, 64), (2, 32), (1, 16), (0, 8)):
            fits = np.flatnonzero(limit - length >= step)
            same = fits[self.ranks[level][a[fits] + length[fits]] == self.ranks[level][b[fits] + length[fits]]]
            length[same] += step
        going = np.flatnonzero(length < limit)
        for _ in range(8):
            going = going[length[going] < limit[going]]
            going = going[self.data[a[going] + length[going]] == self.data[b[going] + length[going]]]
            length[going] += 1
        return length

    def stretches(self, least: int) -> tuple[np.ndarray, np.ndarray]:
        """Places in the order whose suffix shares at least ``least`` (up to 256) bytes with the one before, and how many."""
        a, b = self.order[:-1], self.order[1:]
        both = np.flatnonzero((self.room[a] >= least) & (self.room[b] >= least))
        both = both[self.ranks[4][a[both]] == self.ranks[4][b[both]]] if least >= 128 else both
        length = self.common(a[both], b[both])
        long = length >= least
        return both[long] + 1, np.minimum(length[long], DEPTH)

    def left_of(self, positions: np.ndarray) -> np.ndarray:
        """The byte before each suffix; -1 - position at a string's beginning, which equals none."""
        begins = self.first[:-1][self.string[positions]] == positions
        return np.where(begins, -1 - positions, self.data[np.maximum(positions - 1, 0)])

    def maximal_repeats(self, least: int) -> Iterator[tuple[int, np.ndarray]]:
        """(length, positions of all occurrences) of every maximal repeat: an interval of the order whose suffixes share a prefix that
        can't be prolonged to the right for all, and, as the bytes before its occurrences differ, nor to the left."""
        places, lengths = self.stretches(least)
        if not len(places):
            return
        left = self.left_of(self.order)
        begins = np.flatnonzero(np.append(True, np.diff(places) != 1))
        ends = np.append(begins[1:], len(places))
        # a stretch of two suffixes is one interval: most of them can be prolonged to the left and go all at once
        two = begins[ends - begins == 1]
        at = places[two]
        for i in two[(left[at - 1] != left[at]) | (lengths[two] == DEPTH)].tolist():
            yield int(lengths[i]), self.order[places[i] - 1 : places[i] + 1]
        more = ends - begins > 1
        for a, b in zip(begins[more].tolist(), ends[more].tolist()):
            low, high = int(places[a]) - 1, int(places[b - 1]) + 1
            yield from self._scan(self.order[low:high], lengths[a:b].tolist(), left[low:high].tolist())

    @staticmethod
    def _scan(positions: np.ndarray, shared: list[int], left: list[int]) -> Iterator[tuple[int, np.ndarray]]:
        """Stack scan of one stretch. An open interval: its length, where it begins, and the byte on its left, None once they differ."""
        stack: list[list] = []
        for i in range(1, len(left) + 1):
            length = shared[i - 1] if i <= len(shared) else 0
            begin, byte = i - 1, left[i - 1]
            while stack and stack[-1][0] > length:
                open_length, begin, seen = stack.pop()
                byte = seen if seen == byte else None
                if byte is None or open_length == DEPTH:  # what lies beyond that depth isn't known: such repeats are all given
                    yield open_length, positions[begin:i]
            if not length:
                break
            if stack and stack[-1][0] == length:
                if stack[-1][2] != byte:
                    stack[-1][2] = None
            else:
                stack.append([length, begin, byte])
