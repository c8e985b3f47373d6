"""Brute force over ordered edge subsets, for tests on tiny graphs."""

from __future__ import annotations

from itertools import combinations

from ..motif import Motif


def matches(edges: list[tuple[int, int, int, int, int]], motif: Motif, delta: int, ties: str = "strict") -> list[tuple[int, ...]]:
    """edges: rows (edge_id, src, dst, t, tie); returns the edge id tuples (predicates are not looked at)."""
    rows, out = sorted(edges, key=lambda e: (e[3], e[4])), []
    for chosen in combinations(rows, len(motif)):
        times = [e[3] for e in chosen]
        if times[-1] - times[0] > delta or ties == "strict" and any(a == b for a, b in zip(times, times[1:], strict=False)):
            continue
        image: dict[int, int] = {}
        if all(image.setdefault(x, y) == y for (u, v), e in zip(motif.edges, chosen, strict=True) for x, y in ((u, e[1]), (v, e[2]))) and len(set(image.values())) == len(image):
            out.append(tuple(e[0] for e in chosen))
    return out
