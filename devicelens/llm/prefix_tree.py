"""A prefix tree of sets in one global order, and the similarity join that traverses it."""

from __future__ import annotations

import numpy as np

PERCENT = 85


def least_overlap(a: int, b: int, percent: int = PERCENT) -> int:
    """The least intersection with which sets of these sizes are similar: percent of their union."""
    return -(-percent * (a + b) // (100 + percent))


class UnionFind:
    def __init__(self, n: int):
        self.parent = list(range(n))

    def find(self, i: int) -> int:
        while self.parent[i] != i:
            self.parent[i] = self.parent[self.parent[i]]
            i = self.parent[i]
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.find(i), self.find(j)
        self.parent[max(i, j)] = min(i, j)


class _Node:
    """A run of ranks that all sets below share, the branches after it, and the sets that end with it."""

    __slots__ = ("run", "branches", "ends", "most", "least", "member", "mixed")

    def __init__(self, run: np.ndarray, size: int, member: int):
        self.run, self.branches, self.ends = run, {}, []
        self.most = self.least = size
        self.member, self.mixed = member, False  # one set below; whether sets of other components stand below too

    def split(self, at: int) -> None:
        """Cuts the run; what followed becomes a branch."""
        below = _Node(self.run[at:], self.most, self.member)
        below.branches, below.ends, below.least, below.mixed = self.branches, self.ends, self.least, self.mixed
        self.branches, self.ends, self.run = {int(below.run[0]): below}, [], self.run[:at]


class PrefixTree:
    """Sets, each ascending in the global order and with its full size (elements that no other set has may be left out)."""

    def __init__(self, forest: UnionFind, percent: int = PERCENT):
        self.forest, self.percent, self.root = forest, percent, None

    def _same(self, a: int, b: int) -> bool:
        return self.forest.find(a) == self.forest.find(b)

    def _settled(self, node: _Node) -> bool:
        """Whether all sets below belong to one component by now; components only grow, so it stays true."""
        if node.mixed:
            node.mixed = any(b.mixed or not self._same(b.member, node.member) for b in node.branches.values()) or any(not self._same(m, node.member) for m, _ in node.ends)
        return not node.mixed

    def add(self, ranks: np.ndarray, size: int, member: int) -> None:
        if self.root is None:
            self.root = _Node(ranks[:0], size, member)
        node, at = self.root, 0
        while True:
            node.most, node.least = max(node.most, size), min(node.least, size)
            node.mixed = node.mixed or not self._same(node.member, member)
            n = min(len(node.run), len(ranks) - at)
            differs = np.flatnonzero(node.run[:n] != ranks[at : at + n])
            shared = int(differs[0]) if len(differs) else n
            if shared < len(node.run):
                node.split(shared)
            at += shared
            if at == len(ranks):
                node.ends.append((member, size))
                return
            following = node.branches.get(int(ranks[at]))
            if following is None:
                node.branches[int(ranks[at])] = leaf = _Node(ranks[at:], size, member)
                leaf.ends.append((member, size))
                return
            node = following

    def similar(self, inside: np.ndarray, count: int, size: int, query: int) -> int | None:
        """A member of another component that is similar to a set, given as flags over ranks. Subtrees share the overlap of their
        path; one is left as soon as too many of its path's ranks are missing, too few can follow, or all below it is linked to
        the query already."""
        todo = [(self.root, 0, 0)] if self.root else []
        while todo:
            node, overlap, missed = todo.pop()
            if self._settled(node) and self._same(node.member, query):
                continue
            hits = int(np.count_nonzero(inside[node.run]))
            overlap, missed = overlap + hits, missed + len(node.run) - hits
            most = min(node.most, size * 100 // self.percent)
            if most < node.least or missed > most - least_overlap(size, most, self.percent):
                continue
            if overlap + min(count - overlap, most - overlap - missed) < least_overlap(size, max(node.least, -(-size * self.percent // 100)), self.percent):
                continue
            for member, other in node.ends:
                if overlap >= least_overlap(size, other, self.percent) and not self._same(member, query):
                    return member
            todo += [(branch, overlap, missed) for branch in node.branches.values()]
        return None


def linked(sets: list[np.ndarray], sizes: list[int], percent: int = PERCENT, queries: set[int] | None = None) -> UnionFind:
    """Joins the members of sets (ranks from 0, ascending) that are similar, directly or over others.

    With ``queries`` only pairs of a query and another set are looked at.
    """
    forest = UnionFind(len(sets))
    width = 1 + max((int(s[-1]) for s in sets if len(s)), default=0)
    inside = np.zeros(width, bool)
    tree = PrefixTree(forest, percent)
    order = sorted(range(len(sets)), key=lambda i: (sizes[i], i))
    if queries is not None:
        for i in order:
            if i not in queries:
                tree.add(sets[i], sizes[i], i)
    for i in order:
        if queries is not None and i not in queries:
            continue
        inside[sets[i]] = True
        while (near := tree.similar(inside, len(sets[i]), sizes[i], i)) is not None:
            forest.join(i, near)
        inside[sets[i]] = False
        if queries is None:
            tree.add(sets[i], sizes[i], i)
    return forest
