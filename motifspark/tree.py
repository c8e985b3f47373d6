"""The prefix tree of a motif group: edges shared in the same order stand in it once."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from .motif import Edge, Motif, pattern_text, two_colourable


@dataclass
class Node:
    """A retained prefix: it is a query, or the group divides after it, or it is the root."""

    pattern: tuple[Edge, ...]
    query: str | None = None
    children: list[Node] = field(default_factory=list)

    @property
    def text(self) -> str:
        return pattern_text(self.pattern)


class PrefixTree:
    def __init__(self, root: Node, queries: list[str], aliases: dict[str, str]):
        self.root, self.queries, self.aliases = root, queries, aliases

    @classmethod
    def build(cls, motifs: list[Motif], dedupe: bool = True) -> PrefixTree:
        """Members that are equal after relabelling are mined once and reported under each name (``aliases``)."""
        first: dict[tuple[Edge, ...], str] = {}
        aliases, members = {}, []
        for m in motifs:
            key = m.canonical().keys()
            if key in first:
                if not dedupe:
                    raise ValueError(f"{m.name} equals {first[key]}")
                aliases[m.name] = first[key]
            else:
                first[key] = m.name
                members.append((m.name, key))
        if not members:
            raise ValueError("an empty group")
        names = [m.name for m in motifs]
        if len(set(names)) != len(names):
            raise ValueError("names repeat")
        if len(members) == 1:
            root = Node((), None, [Node(members[0][1], members[0][0])])
        else:
            root = _grown(_shared(members, 0), members)
        return cls(root, names, aliases)

    def nodes(self) -> Iterator[tuple[Node, Node | None]]:
        """Each node with its parent, parents first, siblings in their fixed order."""
        todo: list[tuple[Node, Node | None]] = [(self.root, None)]
        while todo:
            node, parent = todo.pop()
            yield node, parent
            todo += [(c, node) for c in reversed(node.children)]

    def similarity(self) -> float:
        """1 - edges of the tree / edges of its queries."""
        tree = sum(len(n.pattern) - (len(p.pattern) if p else 0) for n, p in self.nodes())
        return 1 - tree / sum(len(n.pattern) for n, _ in self.nodes() if n.query)

    def prefixes(self) -> list[tuple[Edge, ...]]:
        """Every distinct non-empty prefix, parents first: the tree without path compression."""
        out: dict[tuple[Edge, ...], None] = {}
        for node, parent in self.nodes():
            for k in range((len(parent.pattern) if parent else 0) + 1, len(node.pattern) + 1):
                out[node.pattern[:k]] = None
        return list(out)

    def query_of(self) -> dict[tuple[Edge, ...], str]:
        return {n.pattern: n.query for n, _ in self.nodes() if n.query}

    def names_of(self, query: str) -> list[str]:
        """A query's own name and its aliases."""
        return [query, *(a for a, q in self.aliases.items() if q == query)]

    def pruned(self, keep) -> PrefixTree:
        """Without the subtrees whose pattern fails ``keep``; their queries stay named (they count 0)."""

        def cut(node: Node) -> Node:
            left = [cut(c) for c in node.children if keep(c.pattern)]
            return Node(node.pattern, node.query, [c for c in left if c.query or c.children])

        root = cut(self.root) if keep(self.root.pattern) else Node(())
        return PrefixTree(root, self.queries, self.aliases)

    def prune_bipartite(self) -> PrefixTree:
        """Patterns with an odd cycle can't lie in a bipartite graph."""
        return self.pruned(two_colourable)

    def split(self, levels: int) -> list[PrefixTree]:
        """Trees that have one child each at the first ``levels`` branchings on every way down; together they are this one.

        A node that stands in several keeps its query in the first of them only.
        """

        def parts(node: Node, left: int) -> list[Node]:
            if not node.children:
                return [node]
            branching = len(node.children) > 1
            if branching and left <= 0:
                return [node]
            below = [p for c in node.children for p in parts(c, left - branching)]
            return [Node(node.pattern, node.query if k == 0 else None, [p]) for k, p in enumerate(below)]

        return [PrefixTree(r, self.queries, self.aliases) for r in parts(self.root, levels)]

    def rows(self) -> list[tuple[str, str | None, int, str | None]]:
        return [(n.text, p.text if p else None, len(n.pattern), n.query) for n, p in self.nodes()]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), "node string, parent string, n_edges int, query string")

    def render(self) -> str:
        def lines(node: Node, depth: int) -> list[str]:
            return [f"{'  ' * depth}{node.text or '(empty)'} [{node.query or '-'}]", *(x for c in node.children for x in lines(c, depth + 1))]

        return "\n".join(lines(self.root, 0))

    def digest(self) -> str:
        return hashlib.sha256(self.render().encode()).hexdigest()[:16]


def _shared(members: list[tuple[str, tuple[Edge, ...]]], at: int) -> int:
    """Length of the longest prefix that all share (their first ``at`` edges agree), up to the shortest member."""
    shortest = min(len(k) for _, k in members)
    while at < shortest and len({k[at] for _, k in members}) == 1:
        at += 1
    return at


def _grown(depth: int, members: list[tuple[str, tuple[Edge, ...]]]) -> Node:
    node = Node(members[0][1][:depth], next((n for n, k in members if len(k) == depth), None))
    following: dict[Edge, list] = {}
    for name, key in members:
        if len(key) > depth:
            following.setdefault(key[depth], []).append((name, key))
    node.children = [_grown(_shared(group, depth + 1), group) for group in following.values()]
    return node


def similarity_by_prefix(motifs: list[Motif]) -> float:
    """The same measure from distinct prefixes: 1 - their number / edges of the distinct members."""
    keys = {m.canonical().keys() for m in motifs}
    return 1 - len({k[:i] for k in keys for i in range(1, len(k) + 1)}) / sum(map(len, keys))
