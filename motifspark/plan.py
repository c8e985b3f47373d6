"""Lowering: how a partial match takes its next edge."""

from __future__ import annotations

from dataclasses import dataclass

from .motif import Edge


@dataclass(frozen=True)
class Step:
    """kind: root, out (source bound), in (destination bound), closed (both), loop, free (neither).

    ``new`` are the labels that the edge binds, by the end that brings them.
    """

    kind: str
    u: int
    v: int
    new: tuple[tuple[str, int], ...]
    where: str | None

    @property
    def anchors(self) -> list[tuple[str, int]]:
        """(end of the edge, bound label) pairs that must be equal."""
        if self.kind == "out":
            return [("src", self.u)]
        if self.kind == "in":
            return [("dst", self.v)]
        if self.kind == "closed" or self.kind == "loop" and not self.new:
            return [("src", self.u), ("dst", self.v)]
        return []


def bound(prefix: tuple[Edge, ...]) -> int:
    """Number of labels a canonical prefix binds."""
    return max((max(u, v) for u, v, _ in prefix), default=-1) + 1


def step(prefix: tuple[Edge, ...]) -> Step:
    """The step that leads to the prefix from the one before it."""
    n, (u, v, where) = bound(prefix[:-1]), prefix[-1]
    if u == v:
        return Step("root" if len(prefix) == 1 else "loop", u, v, (("src", u),) if u >= n else (), where)
    new = tuple((end, x) for end, x in (("src", u), ("dst", v)) if x >= n)
    kind = "root" if len(prefix) == 1 else {0: "closed", 2: "free"}.get(len(new)) or ("in" if new[0][0] == "src" else "out")
    return Step(kind, u, v, new, where)


def lower(prefixes: list[tuple[Edge, ...]]) -> list[Step]:
    return [step(p) for p in prefixes]
