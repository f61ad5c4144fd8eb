"""Which wide tables to count so that all wanted marginals are sums over one of them."""

from __future__ import annotations

from collections.abc import Iterable

from dpsynth.domain import DomainSpec

Subset = tuple[int, ...]


def cover_plan(wanted: Iterable[Subset], spec: DomainSpec, cap: int = 1_000_000) -> dict[Subset, Subset]:
    """wanted set -> wide set that is counted.

    Greedy: the largest sets first; each joins the wide set that grows least and stays within
    ``cap`` cells, or opens a new one.  Fewer wide sets mean fewer rows on the map side per
    record; the cap bounds what a task's hash table and the shuffle hold.
    """
    wanted = sorted(set(wanted), key=lambda r: (-len(r), -spec.size(r), r))
    wide: list[set[int]] = []
    for r in wanted:
        need, best, at = set(r), None, -1
        for i, w in enumerate(wide):
            if need <= w:
                best, at = 0, i
                break
            cells = spec.size(w | need)
            if cells <= cap and (best is None or cells - spec.size(w) < best):
                best, at = cells - spec.size(w), i
        if at < 0:
            wide.append(need)
        else:
            wide[at] |= need
    final = [tuple(sorted(w)) for w in wide]
    return {r: min((w for w in final if set(r) <= set(w)), key=lambda w: (spec.size(w), w)) for r in wanted}
