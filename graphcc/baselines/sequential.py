"""Sequential union-find with its ablations: the single-machine baseline and the oracle of small tests."""

from __future__ import annotations

from array import array
from collections.abc import Iterable


class DisjointSets:
    """Weighted quick-union with path compression; either part can be switched off."""

    def __init__(self, weighted: bool = True, compress: bool = True):
        self.weighted, self.compress = weighted, compress
        self.parent: dict[int, int] = {}
        self.size: dict[int, int] = {}

    def find(self, x: int) -> int:
        parent = self.parent
        if x not in parent:
            parent[x], self.size[x] = x, 1
            return x
        root = x
        while parent[root] != root:
            root = parent[root]
        if self.compress:
            while parent[x] != root:
                parent[x], x = root, parent[x]
        return root

    def union(self, a: int, b: int) -> tuple[int, int] | None:
        """Link two trees; ``(end on the side that lost its root, root that won)``, None if already one tree."""
        ra, rb = self.find(a), self.find(b)
        if ra == rb:
            return None
        if self.weighted and self.size[ra] < self.size[rb]:
            won, lost, end = rb, ra, a
        else:
            won, lost, end = ra, rb, b
        self.parent[lost] = won
        self.size[won] += self.size[lost]
        return end, won

    def depth(self) -> int:
        """Longest path to a root, without changing the trees."""
        known: dict[int, int] = {}
        for x in self.parent:
            path = []
            while x not in known and self.parent[x] != x:
                path.append(x)
                x = self.parent[x]
            d = known.get(x, 0)
            for y in reversed(path):
                d += 1
                known[y] = d
        return max(known.values(), default=0)


class DenseSets(DisjointSets):
    """The same over the nodes 0 to n - 1, in two arrays: 16 bytes a node."""

    def __init__(self, n: int, weighted: bool = True, compress: bool = True):
        self.weighted, self.compress = weighted, compress
        self.parent, self.size = array("q", range(n)), array("q", [1]) * n

    def find(self, x: int) -> int:
        parent, root = self.parent, x
        while (up := parent[root]) != root:
            root = up
        if self.compress:
            while (up := parent[x]) != root:
                parent[x], x = root, up
        return root

    def depth(self) -> int:
        raise NotImplementedError("depths are measured on DisjointSets")


def union_find(pairs: Iterable[tuple[int, int]], weighted: bool = True, compress: bool = True) -> dict[int, int]:
    """node -> root for all ends of ``pairs``."""
    sets = DisjointSets(weighted, compress)
    for a, b in pairs:
        sets.union(a, b)
    return {x: sets.find(x) for x in list(sets.parent)}
