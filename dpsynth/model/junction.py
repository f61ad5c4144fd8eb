"""Junction trees over attributes, and how large they are."""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from dataclasses import dataclass

Subset = tuple[int, ...]


def _neighbours(sets: Iterable[Subset], d: int) -> list[set[int]]:
    near: list[set[int]] = [set() for _ in range(d)]
    for r in sets:
        for i in r:
            near[i].update(r)
    for i in range(d):
        near[i].discard(i)
    return near


def elimination_cliques(sets: Iterable[Subset], sizes: Sequence[int]) -> list[Subset]:
    """Maximal cliques of a triangulation: the attribute whose clique is smallest goes first."""
    near = _neighbours(sets, len(sizes))
    left, cliques = set(range(len(sizes))), []

    def cells(i: int) -> int:
        out = sizes[i]
        for j in near[i]:
            out *= sizes[j]
        return out

    cost = {i: cells(i) for i in left}
    while left:
        i = min(left, key=lambda x: (cost[x], x))
        clique = near[i] | {i}
        if not any(clique <= c for c in cliques):
            cliques.append(clique)
        for j in near[i]:
            near[j] |= near[i]
            near[j] -= {i, j}
        left.discard(i)
        touched = {k for j in near[i] for k in (near[j] | {j})}
        for k in touched & left:
            cost[k] = cells(k)
    return [tuple(sorted(c)) for c in cliques]


def size_mb(sets: Iterable[Subset], sizes: Sequence[int]) -> float:
    """Megabytes of the clique tables that measuring ``sets`` would need, 8 bytes a cell."""
    total = 0
    for c in elimination_cliques(sets, sizes):
        cells = 1
        for i in c:
            cells *= sizes[i]
        total += cells
    return total * 8 / 2**20


@dataclass(frozen=True)
class JunctionTree:
    """cliques in an order in which each one's parent precedes it; parent -1 marks a root."""

    cliques: tuple[Subset, ...]
    parent: tuple[int, ...]

    @classmethod
    def of(cls, sets: Iterable[Subset], sizes: Sequence[int]) -> JunctionTree:
        """Maximum-separator spanning forest over the elimination cliques."""
        cliques = elimination_cliques(sets, sizes)
        order, parent = [], []
        left = list(range(len(cliques)))
        while left:
            best = (-1, left[0], -1)
            for c in left:
                for k, placed in enumerate(order):
                    shared = len(set(cliques[c]) & set(cliques[placed]))
                    if shared and shared > best[0]:
                        best = (shared, c, k)
            order.append(best[1])
            parent.append(best[2] if best[0] > 0 else -1)
            left.remove(best[1])
        return cls(tuple(cliques[c] for c in order), tuple(parent))

    def home(self, subset: Iterable[int], sizes: Sequence[int]) -> int:
        """The smallest clique that holds the subset, or -1."""
        need, best, at = set(subset), None, -1
        for k, c in enumerate(self.cliques):
            if need <= set(c):
                cells = 1
                for i in c:
                    cells *= sizes[i]
                if best is None or cells < best:
                    best, at = cells, k
        return at
