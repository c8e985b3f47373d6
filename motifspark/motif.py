"""Motifs: small patterns of edges in time order."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

Edge = tuple[int, int, str | None]  # source and destination label, predicate on the data edge


@dataclass(frozen=True)
class Motif:
    """An ordered list of edges between labelled vertices.

    ``where`` holds an SQL predicate on the data edge (or None) for each position.
    """

    name: str
    edges: tuple[tuple[int, int], ...]
    where: tuple[str | None, ...] = field(default=())

    def __post_init__(self):
        if not self.edges:
            raise ValueError(f"motif {self.name}: no edges")
        if any(len(e) != 2 or min(e) < 0 for e in self.edges):
            raise ValueError(f"motif {self.name}: an edge is a pair of labels from 0")
        if not self.where:
            object.__setattr__(self, "where", (None,) * len(self.edges))
        if len(self.where) != len(self.edges):
            raise ValueError(f"motif {self.name}: one predicate an edge")

    @classmethod
    def parse(cls, name: str, text: str) -> Motif:
        """``"AB BC CA"`` or ``"A>B, B>C, C>A"``; letters in any alphabet order."""
        parts = [p for p in re.split(r"[\s,;]+", text.strip()) if p]
        ends = [tuple(p.split(">")) if ">" in p else tuple(p) for p in parts]
        if any(len(e) != 2 or not all(e) for e in ends):
            raise ValueError(f"motif {name}: can't read {text!r}")
        number: dict[str, int] = {}
        return cls(name, tuple((number.setdefault(a, len(number)), number.setdefault(b, len(number))) for a, b in ends))

    def with_predicate(self, position: int, expression: str) -> Motif:
        """The data edge at the position must also fulfil the expression (on etype, weight and other edge columns)."""
        w = list(self.where)
        w[position] = expression if w[position] is None else f"({w[position]}) AND ({expression})"
        return Motif(self.name, self.edges, tuple(w))

    def with_label(self, vertex: int, value: str) -> Motif:
        """The data vertex must carry the label (columns slabel and dlabel of a graph with vertices)."""
        quoted = value.replace("'", "''")
        for position, (u, v) in enumerate(self.edges):
            if vertex in (u, v):
                return self.with_predicate(position, f"{'slabel' if vertex == u else 'dlabel'} = '{quoted}'")
        raise ValueError(f"motif {self.name}: no vertex {vertex}")

    def canonical(self) -> Motif:
        """Labels by first appearance, so equal prefixes are equal tuples whatever letters were used."""
        number: dict[int, int] = {}
        return Motif(self.name, tuple((number.setdefault(u, len(number)), number.setdefault(v, len(number))) for u, v in self.edges), self.where)

    def edge_at(self, position: int) -> Edge:
        return (*self.edges[position], self.where[position])

    def keys(self) -> tuple[Edge, ...]:
        """The edges as the tree compares them."""
        return tuple(self.edge_at(k) for k in range(len(self.edges)))

    def prefix(self, k: int) -> tuple[Edge, ...]:
        return self.keys()[:k]

    def __len__(self) -> int:
        return len(self.edges)

    @property
    def text(self) -> str:
        return pattern_text(self.canonical().keys())

    def is_odd_cycle_free(self) -> bool:
        return two_colourable(self.canonical().keys())


def letter(v: int) -> str:
    return "ABCDEFGHIJKLMNOPQRSTUVWXYZ"[v] if v < 26 else f"V{v}"


def pattern_text(edges: tuple[Edge, ...]) -> str:
    """``AB BC CA``; a predicate follows its edge in brackets, the empty pattern is empty."""
    return " ".join(letter(u) + letter(v) + (f"[{w}]" if w else "") for u, v, w in edges)


def two_colourable(edges: tuple[Edge, ...]) -> bool:
    """Whether the pattern, seen without directions, fits a bipartite graph."""
    near: dict[int, set[int]] = {}
    for u, v, _ in edges:
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    side: dict[int, int] = {}
    for start in near:
        if start in side:
            continue
        side[start], todo = 0, [start]
        while todo:
            x = todo.pop()
            for y in near[x]:
                if y not in side:
                    side[y] = 1 - side[x]
                    todo.append(y)
                elif side[y] == side[x]:
                    return False
    return True
