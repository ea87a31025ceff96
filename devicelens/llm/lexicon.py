"""A minimal acyclic automaton of words with id sequences as outputs, laid out as flat arrays that can be memory-mapped.

Words come in sorted order; states with equal right languages are shared as the automaton grows, so common suffixes are stored once.
An arc carries how many words come before those behind it; their sum along a path is the word's place in the sorted list,
and that is the index of its output: outputs survive the sharing of suffixes.
"""

from __future__ import annotations

import mmap
import struct
from collections.abc import Iterable, Sequence

import numpy as np

_HEAD = struct.Struct("<4sIIIII")  # mark, slots, words, states, ids, length of the longest word
_MARK = b"MADL"


class _State:
    __slots__ = ("arcs", "final", "words")

    def __init__(self) -> None:
        self.arcs: dict[int, _State] = {}
        self.final = False
        self.words = -1

    def signature(self) -> tuple:
        return (self.final, *((b, id(s)) for b, s in self.arcs.items()))

    def count(self) -> int:
        if self.words < 0:
            self.words = self.final + sum(s.count() for s in self.arcs.values())
        return self.words


def minimal_automaton(words: Iterable[bytes]) -> _State:
    """The automaton of distinct words in ascending order."""
    root, register = _State(), {}
    path: list[tuple[_State, int, _State]] = []
    last = b""

    def settle(depth: int) -> None:
        while len(path) > depth:
            parent, label, child = path.pop()
            parent.arcs[label] = register.setdefault(child.signature(), child)

    for word in words:
        shared = 0
        while shared < min(len(word), len(last)) and word[shared] == last[shared]:
            shared += 1
        settle(shared)
        state = path[-1][2] if path else root
        for label in word[shared:]:
            state.arcs[label] = child = _State()
            path.append((state, label, child))
            state = child
        state.final = True
        last = word
    settle(0)
    return root


def compile_lexicon(entries: dict[bytes, Sequence[int]]) -> bytes:
    """The flat form: a double array of arcs (base, owner, target, words skipped), which states are final, and the ids in word order with where
    each word's begin."""
    words = sorted(w for w in entries if w)
    root = minimal_automaton(words)
    states: dict[int, int] = {}
    order: list[_State] = []
    todo = [root]
    while todo:
        state = todo.pop()
        if id(state) not in states:
            states[id(state)] = len(order)
            order.append(state)
            todo += state.arcs.values()
    base, taken = [0] * len(order), bytearray(4096)
    full = 0  # no slot before this one is free
    for i in sorted(range(len(order)), key=lambda i: -len(order[i].arcs)):
        if not order[i].arcs:
            continue
        lead, *labels = order[i].arcs
        slot, tries = taken.find(0, max(full, lead)), 0
        while any(taken[slot - lead + b] for b in labels):
            slot, tries = taken.find(0, slot + 1), tries + 1
            if slot + 512 > len(taken):
                taken += bytes(len(taken))
        if tries > 500:
            full = max(full, slot - 4096)  # the few slots left there take too long to fill
        if slot + 1024 > len(taken):
            taken += bytes(len(taken))
        base[i] = slot - lead
        for b in (lead, *labels):
            taken[base[i] + b] = 1
        if not labels:
            full = max(full, slot - 256)
    slots = max((base[i] + b for i, s in enumerate(order) for b in s.arcs), default=0) + 257
    owner, target, skipped = [-1] * slots, [0] * slots, [0] * slots
    for i, state in enumerate(order):
        before = int(state.final)
        for b in sorted(state.arcs):
            at = base[i] + b
            owner[at], target[at], skipped[at] = i, states[id(state.arcs[b])], before
            before += state.arcs[b].count()
    ids = np.array([i for w in words for i in entries[w]], np.int32)
    begins = np.cumsum([0, *(len(entries[w]) for w in words)])
    arrays = (owner, target, skipped, base, [int(s.final) for s in order], begins, ids)
    return _HEAD.pack(_MARK, slots, len(words), len(order), len(ids), max(map(len, words), default=0)) + b"".join(np.asarray(x, np.int32).tobytes() for x in arrays)


class Lexicon:
    """Looks words up in a compiled lexicon, mapped from its file."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self._map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        mark, slots, words, states, ids, self.longest = _HEAD.unpack_from(self._map)
        if mark != _MARK:
            raise ValueError(f"{path} holds no lexicon")
        parts, at = [], _HEAD.size
        for n in (slots, slots, slots, states, states, words + 1, ids):
            parts.append(np.frombuffer(self._map, np.int32, n, at))
            at += 4 * n
        self.owner, self.target, self.skipped, self.base, self.final, self.begins, self.ids = parts

    def find(self, words: list[bytes]) -> list[int]:
        """The place of each word, -1 for one that isn't there; all words walk the automaton together, a byte a step."""
        lengths = np.array([len(w) for w in words], np.int64)
        data, starts = np.frombuffer(b"".join(words), np.uint8), np.cumsum(lengths) - lengths
        places = np.full(len(words), -1, np.int64)
        going = np.flatnonzero((lengths > 0) & (lengths <= self.longest))
        state, place = np.zeros(len(going), np.int64), np.zeros(len(going), np.int64)
        step = 0
        while len(going):
            at = self.base[state] + data[starts[going] + step]
            fits = self.owner[at] == state
            going, at = going[fits], at[fits]
            state, place = self.target[at], place[fits] + self.skipped[at]
            step += 1
            ends = lengths[going] == step
            full = ends & (self.final[state] > 0)
            places[going[full]] = place[full]
            going, state, place = going[~ends], state[~ends], place[~ends]
        return places.tolist()

    def output(self, place: int) -> bytes:
        """The ids of a word, as 32-bit numbers."""
        return self.ids[self.begins[place] : self.begins[place + 1]].tobytes()

    def get(self, word: bytes) -> list[int] | None:
        place = self.find([word])[0]
        return np.frombuffer(self.output(place), np.int32).tolist() if place >= 0 else None
