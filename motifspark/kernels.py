"""In-task kernels: co-mining of one slab's edges in numpy, over blocks of root edges.

A slab's edges become three adjacencies (by source, by destination, by pair), each sorted
by vertex and time rank, so that the candidates of a partial match are one range found by
binary search.  ``generic`` interprets the tree's steps; ``specialised`` emits straight-line
Python for the tree, compiles it once a task and keeps it by the tree's digest.  Both look
at a whole block of partial matches at a time, with one boolean mask instead of branches.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np

from .motif import Edge
from .plan import bound, step
from .tree import PrefixTree

#: Root edges, and partial matches, that a kernel extends together.
BLOCK = 1 << 16
#: Candidates a row from which last edges are counted by ranks and not looked at, for each vertex that a new one must differ from.
FEW = 4


class Adjacency:
    """Edges of a slab in arrays, ordered by (t, tie, id); ranks stand for times."""

    def __init__(self, edge_id, src, dst, t, tie, ties: str = "strict", passes: dict[str, np.ndarray] | None = None, weight: np.ndarray | None = None):
        order = np.lexsort((edge_id, tie, t))
        self.order = order
        self.edge_id, self.src, self.dst, self.t, self.tie = (np.asarray(x)[order] for x in (edge_id, src, dst, t, tie))
        self.passes = {k: v[order] for k, v in (passes or {}).items()}
        n = len(order)
        ids, dense = np.unique(np.concatenate((self.src, self.dst)), return_inverse=True)
        self.s, self.d = dense[:n].astype(np.int64), dense[n:].astype(np.int64)
        self.vertices, self.ids = len(ids), ids
        # With strict order equal times share a rank, else equal (t, tie).
        later = self.t[1:] != self.t[:-1]
        if ties != "strict":
            later |= self.tie[1:] != self.tie[:-1]
        self.rank = np.concatenate((np.zeros(min(n, 1), dtype=np.int64), np.cumsum(later)))
        self.span = n + 1
        self.by: dict[str, tuple[np.ndarray, np.ndarray]] = {}
        for name, key in (("src", self.s), ("dst", self.d), ("pair", self.s * self.vertices + self.d), ("all", np.zeros(n, dtype=np.int64))):
            composite = key * self.span + self.rank
            at = np.argsort(composite, kind="stable")
            self.by[name] = (composite[at], at)
        #: The rank of the newest edge of each pair, by a hash of the pair (of several in one slot the newest's); none: -1.
        self.bits = max(4, (2 * n).bit_length())
        self.newest = np.full(1 << self.bits, -1, dtype=np.int32 if n < 1 << 31 else np.int64)
        self.newest[self.slot(self.s * self.vertices + self.d)] = self.rank  # ranks ascend, the last one stays
        self._known: dict[tuple, np.ndarray] = {}
        #: How many edges a row stands for, and sums of that in each order.
        self.weight = None if weight is None else np.asarray(weight)[order]
        self.upto = {} if weight is None else {k: np.concatenate((np.zeros(1, dtype=np.int64), np.cumsum(self.weight[at]))) for k, (_, at) in self.by.items()}

    def slot(self, pair: np.ndarray) -> np.ndarray:
        return ((pair.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def known(self, name: tuple, make: Callable[[], np.ndarray]) -> np.ndarray:
        """An array with a number an edge, made when first asked for."""
        if name not in self._known:
            self._known[name] = make().astype(self.newest.dtype)
        return self._known[name]

    def reach(self, delta: int) -> np.ndarray:
        """For each edge the highest rank in a window that it opens."""
        return self.known(("reach", delta), lambda: self.last_rank(self.t + delta))

    def after(self, which: str, end: str) -> np.ndarray:
        """For each edge where those begin, in the order of ``which``, that come after it and have its end ("s" or "d") as their key."""
        return self.known((which, end), lambda: np.searchsorted(self.by[which][0], getattr(self, end) * self.span + self.rank, "right"))

    def upper(self, which: str, end: str, delta: int) -> np.ndarray:
        """For each edge where those end that have its end as their key and lie in a window that it opens."""
        return self.known((which, end, delta), lambda: np.searchsorted(self.by[which][0], getattr(self, end) * self.span + self.reach(delta), "right"))

    def last_rank(self, until: np.ndarray) -> np.ndarray:
        """The highest rank of an edge not later than the time."""
        at = np.searchsorted(self.t, until, "right") - 1
        return np.where(at >= 0, self.rank[np.maximum(at, 0)], -1)

    def place_of(self, t: np.ndarray, tie: np.ndarray) -> np.ndarray:
        """The first edge with the time and the tie, which must be there: a binary search for all at once."""
        lo, hi = np.searchsorted(self.t, t, "left"), np.searchsorted(self.t, t, "right")
        while (lo < hi).any():
            mid = (lo + hi) // 2
            less = (lo < hi) & (self.tie[np.minimum(mid, len(self.t) - 1)] < tie)
            lo, hi = np.where(less, mid + 1, lo), np.where((lo < hi) & ~less, mid, hi)
        return np.minimum(lo, len(self.t) - 1)

    def spans(self, which: str, key: np.ndarray, after: np.ndarray, until: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each row where its candidates begin, and how many there are: edges with the key whose rank lies in (after, until].

        Most pairs have no edge after a given one: only those that may have one are searched.
        """
        composite, _ = self.by[which]
        if which == "pair":
            some = np.flatnonzero(self.newest[self.slot(key)] > after)
            begin, size = np.zeros(len(key), dtype=np.int64), np.zeros(len(key), dtype=np.int64)
            key, after, until = key[some], after[some], until[some]
            begin[some] = lo = np.searchsorted(composite, key * self.span + after, "right")
            size[some] = np.maximum(np.searchsorted(composite, key * self.span + until, "right") - lo, 0)
            return begin, size
        lo = np.searchsorted(composite, key * self.span + after, "right")
        return lo, np.maximum(np.searchsorted(composite, key * self.span + until, "right") - lo, 0)

    def weighed(self, which: str, key: np.ndarray, after: np.ndarray, until: np.ndarray) -> np.ndarray:
        """For each row how many edges its candidates stand for."""
        lo, size = self.spans(which, key, after, until)
        return self.upto[which][lo + size] - self.upto[which][lo]

    def others(self, which: str, key: np.ndarray, bound: list[np.ndarray], after: np.ndarray, until: np.ndarray, size: np.ndarray | None = None) -> int | None:
        """How many candidates (``size`` a row, if known) end in none of the bound vertices: all less those to each of them, by ranks.  None: so few that looking at them is cheaper."""
        n = int((self.spans(which, key, after, until)[1] if size is None else size).sum())
        if n <= FEW * (len(bound) + 1) * len(key):
            return None
        for x in bound:
            n -= int(self.spans("pair", key * self.vertices + x if which == "src" else x * self.vertices + key, after, until)[1].sum())
        return n

    def candidates(self, which: str, key: np.ndarray, after: np.ndarray, until: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(row, edge) pairs, in pieces of BLOCK at most: a row with many candidates is cut too."""
        lo, size = self.spans(which, key, after, until)
        for r0, r1, begin, n in cuts(size, BLOCK):
            yield piece(self.by[which][1], lo, r0, r1, begin, n)


def cuts(size: np.ndarray, most: int) -> Iterator[tuple[int, int, int, np.ndarray]]:
    """Rows r0 to r1 whose candidates make a piece of ``most`` at most, how many of the first row's are left out, and their numbers."""
    cum = np.cumsum(size)
    for start in range(0, int(cum[-1]) if len(cum) else 0, most):
        stop = min(start + most, int(cum[-1]))
        r0, r1 = int(np.searchsorted(cum, start, "right")), int(np.searchsorted(cum, stop, "left")) + 1
        n = size[r0:r1].copy()
        begin = start - int(cum[r0] - size[r0])
        n[0] -= begin
        n[-1] -= int(cum[r1 - 1]) - stop
        yield r0, r1, begin, n


def piece(at: np.ndarray, lo: np.ndarray, r0: int, r1: int, begin: int, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    start = lo[r0:r1].copy()
    start[0] += begin
    ends = np.cumsum(n)
    return np.repeat(np.arange(r0, r1), n), at[np.repeat(start - (ends - n), n) + np.arange(int(ends[-1]))]


def lookup(a: Adjacency, p: tuple[Edge, ...], v: list[np.ndarray], rows: int) -> tuple[str, np.ndarray]:
    """Which adjacency the step to p asks, and its keys."""
    s = step(p)
    if s.kind == "out":
        return "src", v[s.u]
    if s.kind == "in":
        return "dst", v[s.v]
    if s.anchors:
        return "pair", v[s.u] * a.vertices + v[s.v]
    return "all", np.zeros(rows, dtype=np.int64)


def admitted(a: Adjacency, p: tuple[Edge, ...], v: list[np.ndarray], row: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Those candidates that the step to p takes: new vertices are new, loops are loops, predicates hold."""
    s, n = step(p), bound(p[:-1])
    ok = np.ones(len(e), dtype=bool)
    for end, _ in s.new:
        x = (a.s if end == "src" else a.d)[e]
        for k in range(n):
            ok &= x != v[k][row]
    if len(s.new) == 2:
        ok &= a.s[e] != a.d[e]
    if s.kind == "loop":
        ok &= a.s[e] == a.d[e]
    if s.where:
        ok &= a.passes[s.where][e]
    return row[ok], e[ok]


def extend(a: Adjacency, p: tuple[Edge, ...], v: list[np.ndarray], last: np.ndarray, until: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, edge) pairs that take partial matches to the prefix p, piece by piece."""
    for row, e in a.candidates(*lookup(a, p, v, len(last)), last, until):
        yield admitted(a, p, v, row, e)


def roots(a: Adjacency, p: tuple[Edge, ...], owned: np.ndarray) -> np.ndarray:
    s = step(p)
    ok = owned & ((a.s == a.d) if s.u == s.v else (a.s != a.d))
    return np.flatnonzero(ok & a.passes[s.where] if s.where else ok)


def children(tree: PrefixTree) -> dict[tuple[Edge, ...], list[tuple[Edge, ...]]]:
    out: dict[tuple[Edge, ...], list[tuple[Edge, ...]]] = {p: [] for p in [(), *tree.prefixes()]}
    for p in tree.prefixes():
        out[p[:-1]].append(p)
    return out


def summed(q: tuple[Edge, ...], following: dict) -> bool:
    """A last edge between two bound vertices, without predicate: its candidates are its matches, a difference of ranks."""
    s = step(q)
    return not following[q] and s.kind == "closed" and not s.where


def open_ended(q: tuple[Edge, ...], following: dict) -> bool:
    """A last edge to one new vertex, without predicate: its matches are its candidates but those that end in a bound vertex."""
    s = step(q)
    return not following[q] and s.kind in ("out", "in") and not s.where


def generic(tree: PrefixTree) -> Callable:
    """kernel(adjacency, owned, delta, keep): an iterator of (query, edges, matches), block by block; edges is a list of arrays."""
    following, queries = children(tree), tree.query_of()

    def descend(a, p, v, e, last, until, keep):
        if p in queries:
            yield queries[p], e, len(last)
        for q in following[p]:
            if not keep and summed(q, following):
                if n := int(a.spans(*lookup(a, q, v, len(last)), last, until)[1].sum()):
                    yield queries[q], [], n
                continue
            for at in range(0, len(last), BLOCK):
                part = slice(at, at + BLOCK)
                pv = [x[part] for x in v]
                if not keep and open_ended(q, following):
                    which, key = lookup(a, q, pv, len(last[part]))
                    n = a.others(which, key, pv, last[part], until[part])
                    if n is not None:
                        if n:
                            yield queries[q], [], n
                        continue
                for row, edge in extend(a, q, pv, last[part], until[part]):
                    if len(edge):
                        grown = [x[row] for x in pv] + [(a.s if end == "src" else a.d)[edge] for end, _ in step(q).new]
                        yield from descend(a, q, grown, [x[part][row] for x in e] + [edge] if keep else e, a.rank[edge], until[part][row], keep)

    def kernel(a: Adjacency, owned: np.ndarray, delta: int, keep: bool = False):
        for p in following[()]:
            every = roots(a, p, owned)
            for at in range(0, len(every), BLOCK):
                r = every[at : at + BLOCK]
                v = [a.s[r]] if p[0][0] == p[0][1] else [a.s[r], a.d[r]]
                yield from descend(a, p, v, [r] if keep else [], a.rank[r], a.last_rank(a.t[r] + delta), keep)

    return kernel


def source(tree: PrefixTree) -> str:
    """Straight-line Python for the tree: one nested loop a prefix, labels and checks written out."""
    following, queries = children(tree), tree.query_of()
    out = ["def kernel(a, owned, delta, keep=False):", "    S, D, R = a.s, a.d, a.rank"]

    def put(depth: int, text: str) -> None:
        out.append("    " * depth + text)

    def level(p: tuple[Edge, ...], d: int) -> None:
        """Inside the loop where frontier k = len(p) lives in variables of that level."""
        k, s, n = len(p), step(p), bound(p)
        if p in queries:
            put(d, f"yield {queries[p]!r}, e{k} if keep else [], len(l{k})")
        for q in following[p]:
            t, m = step(q), n
            put(d, f"for i{k} in range(0, len(l{k}), BLOCK):")
            put(d + 1, f"w{k} = slice(i{k}, i{k} + BLOCK)")
            for x in range(m):
                put(d + 1, f"p{k}_{x} = v{k}_{x}[w{k}]")
            if t.kind == "out":
                which, key = "src", f"p{k}_{t.u}"
            elif t.kind == "in":
                which, key = "dst", f"p{k}_{t.v}"
            elif t.anchors:
                which, key = "pair", f"p{k}_{t.u} * a.vertices + p{k}_{t.v}"
            else:
                which, key = "all", f"p{k}_0 * 0"
            if summed(q, following):
                put(d + 1, "if not keep:")
                put(d + 2, f"n = int(a.spans({which!r}, {key}, l{k}[w{k}], u{k}[w{k}])[1].sum())")
                put(d + 2, f"if n: yield {queries[q]!r}, [], n")
                put(d + 2, "continue")
            if open_ended(q, following):
                put(d + 1, f"n = None if keep else a.others({which!r}, {key}, [{', '.join(f'p{k}_{x}' for x in range(m))}], l{k}[w{k}], u{k}[w{k}])")
                put(d + 1, "if n is not None:")
                put(d + 2, f"if n: yield {queries[q]!r}, [], n")
                put(d + 2, "continue")
            put(d + 1, f"for r, c in a.candidates({which!r}, {key}, l{k}[w{k}], u{k}[w{k}]):")
            checks = [f"({'S' if end == 'src' else 'D'}[c] != p{k}_{x}[r])" for end, _ in t.new for x in range(m)]
            checks += ["(S[c] != D[c])"] * (len(t.new) == 2) + ["(S[c] == D[c])"] * (t.kind == "loop") + [f"a.passes[{t.where!r}][c]"] * bool(t.where)
            if checks:
                put(d + 2, f"o = {' & '.join(checks)}")
                put(d + 2, "r, c = r[o], c[o]")
            if not following[q]:  # a last edge: its matches are told where they are found
                put(d + 2, f"if len(c): yield {queries[q]!r}, [x[w{k}][r] for x in e{k}] + [c] if keep else [], len(c)")
                continue
            put(d + 2, "if len(c):")
            for x in range(m):
                put(d + 3, f"v{k + 1}_{x} = p{k}_{x}[r]")
            for end, x in t.new:
                put(d + 3, f"v{k + 1}_{x} = {'S' if end == 'src' else 'D'}[c]")
            put(d + 3, f"l{k + 1}, u{k + 1} = R[c], u{k}[w{k}][r]")
            put(d + 3, f"e{k + 1} = [x[w{k}][r] for x in e{k}] + [c] if keep else []")
            level(q, d + 3)

    for p in following[()]:
        put(1, f"every = roots(a, {p!r}, owned)")
        put(1, "for i0 in range(0, len(every), BLOCK):")
        put(2, "b = every[i0:i0 + BLOCK]")
        put(2, "v1_0 = S[b]" if p[0][0] == p[0][1] else "v1_0, v1_1 = S[b], D[b]")
        put(2, "l1, u1, e1 = R[b], a.last_rank(a.t[b] + delta), [b]")
        level(p, 2)
    return "\n".join(out)


_COMPILED: dict[str, Callable] = {}


def specialised(tree: PrefixTree) -> Callable:
    key = tree.digest()
    if key not in _COMPILED:
        space = {"roots": roots, "BLOCK": BLOCK}
        exec(compile(source(tree), f"<kernel {key}>", "exec"), space)  # noqa: S102 - the text is made above, from the tree alone
        _COMPILED[key] = space["kernel"]
    return _COMPILED[key]


def tally(kernel: Callable, a: Adjacency, owned: np.ndarray, delta: int) -> dict[str, int]:
    out: dict[str, int] = {}
    for query, _, n in kernel(a, owned, delta):
        out[query] = out.get(query, 0) + n
    return out


def weighted(tree: PrefixTree, a: Adjacency, owned: np.ndarray, delta: int) -> dict[str, int]:
    """Counts where a row stands for several equal edges (strict order only: no two of them lie in one match)."""
    following, queries, out = children(tree), tree.query_of(), {}

    def add(q, n: np.ndarray) -> None:
        out[queries[q]] = out.get(queries[q], 0) + int(n.sum())

    def descend(p, v, w, last, until) -> None:
        if p in queries:
            add(p, w)
        for q in following[p]:
            for at in range(0, len(last), BLOCK):
                part = slice(at, at + BLOCK)
                pv, pw, after, before = [x[part] for x in v], w[part], last[part], until[part]
                which, key = lookup(a, q, pv, len(after))
                if summed(q, following):
                    add(q, pw * a.weighed(which, key, after, before))
                    continue
                if open_ended(q, following) and int(a.spans(which, key, after, before)[1].sum()) > FEW * (len(pv) + 1) * len(after):
                    n = a.weighed(which, key, after, before)
                    for x in pv:
                        n = n - a.weighed("pair", key * a.vertices + x if which == "src" else x * a.vertices + key, after, before)
                    add(q, pw * n)
                    continue
                for row, edge in extend(a, q, pv, after, before):
                    if len(edge) and not following[q]:
                        add(q, pw[row] * a.weight[edge])
                    elif len(edge):
                        grown = [x[row] for x in pv] + [(a.s if end == "src" else a.d)[edge] for end, _ in step(q).new]
                        descend(q, grown, pw[row] * a.weight[edge], a.rank[edge], before[row])

    for p in following[()]:
        every = roots(a, p, owned)
        for at in range(0, len(every), BLOCK):
            r = every[at : at + BLOCK]
            descend(p, [a.s[r]] if p[0][0] == p[0][1] else [a.s[r], a.d[r]], a.weight[r], a.rank[r], a.last_rank(a.t[r] + delta))
    return out


def found(kernel: Callable, a: Adjacency, owned: np.ndarray, delta: int) -> Iterator[tuple[str, list[np.ndarray]]]:
    """Matches as they are found: none are held."""
    for query, e, _ in kernel(a, owned, delta, True):
        yield query, e


class Search:
    """Depth-first search with a stack of contexts, which can stop after some work and be taken up elsewhere.

    A context is a block of partial matches and one child of their prefix: siblings are contexts of
    their own, and contexts of all levels lie on the stack.  Each row of a context has a run of
    candidates (where it begins, how many are left); runs are worked off in pieces.  When the budget of
    candidates is used up, what lies on the stack can be handed over: rows with their runs, the longest
    ones cut.  Where a row of the adjacency stands for several equal edges, each partial match has
    a weight, for how many it stands (counts in strict order only, as in ``weighted``).
    """

    def __init__(self, a: Adjacency, tree: PrefixTree, delta: int, keep: bool = False):
        self.a, self.delta, self.keep = a, delta, keep
        self.following, self.queries = children(tree), tree.query_of()
        self.number = {p: k for k, p in enumerate(tree.prefixes())}
        self.stack: list[tuple] = []
        self.work = 0

    def start(self, owned: np.ndarray) -> Iterator[tuple[str, list[np.ndarray], int]]:
        for p in self.following[()]:
            r = roots(self.a, p, owned)
            v = [self.a.s[r]] if p[0][0] == p[0][1] else [self.a.s[r], self.a.d[r]]
            if len(r):
                yield from self.arrived(p, v, [r] if self.keep else [], r, r, None if self.a.weight is None else self.a.weight[r])

    def arrived(self, p, v, e, first, last, w=None) -> Iterator[tuple[str, list[np.ndarray], int]]:
        """Partial matches of the prefix p: counted if it is a query; its children become contexts."""
        if p in self.queries:
            yield self.queries[p], e, len(last) if w is None else int(w.sum())
        for q in reversed(self.following[p]):
            which, key = lookup(self.a, q, v, len(last))
            after, until = self.a.rank[last], self.a.reach(self.delta)[first]
            lo, size = self.spans(p, q, which, key, first, last)
            if not self.keep and (summed(q, self.following) or open_ended(q, self.following)):
                if w is not None:
                    n = self.weighed(q, which, key, v, after, until, lo, size, w)
                else:
                    n = int(size.sum()) if summed(q, self.following) else self.a.others(which, key, v, after, until, size)
                if n is not None:
                    self.work += len(last)
                    if n:
                        yield self.queries[q], [], n
                    continue
            self.push(q, v, e, first, last, lo, lo, size, w)

    def weighed(self, q, which, key, v, after, until, lo, size, w) -> int | None:
        """How many matches the last edges to q make, by sums of weights.  None: so few candidates that looking at them is cheaper."""
        a, closed = self.a, summed(q, self.following)
        if not closed and int(size.sum()) <= FEW * (len(v) + 1) * len(key):
            return None
        n = a.upto[which][lo + size] - a.upto[which][lo]
        for x in [] if closed else v:
            n = n - a.weighed("pair", key * a.vertices + x if which == "src" else x * a.vertices + key, after, until)
        return int((w * n).sum())

    def spans(self, p, q, which, key, first, last) -> tuple[np.ndarray, np.ndarray]:
        """Adjacency.spans for the step from p to q.  Where the key is an end of the last or the first edge, an array of that edge knows the place and nothing is searched."""
        a, s = self.a, step(q)
        if which not in ("src", "dst"):
            return a.spans(which, key, a.rank[last], a.reach(self.delta)[first])
        x = s.u if which == "src" else s.v
        end = lambda edge: {edge[1]: "d", edge[0]: "s"}.get(x)
        new, old, composite = end(p[-1]), end(p[0]), a.by[which][0]
        lo = a.after(which, new)[last] if new else np.searchsorted(composite, key * a.span + a.rank[last], "right")
        hi = a.upper(which, old, self.delta)[first] if old else np.searchsorted(composite, key * a.span + a.reach(self.delta)[first], "right")
        return lo.astype(np.int64), np.maximum(hi.astype(np.int64) - lo, 0)

    def push(self, q, v, e, first, last, lo0, lo, size, w=None) -> None:
        some = size > 0
        if some.any():
            pick = (lambda x: x) if some.all() else (lambda x: x[some])
            self.stack.append((q, [pick(x) for x in v], [pick(x) for x in e], pick(first), pick(last), pick(lo0), pick(lo), pick(size), None if w is None else pick(w)))

    def run(self, budget: float = float("inf")) -> Iterator[tuple[str, list[np.ndarray], int]]:
        most = BLOCK if budget >= BLOCK else max(1, int(budget))
        while self.stack and self.work < budget:
            q, v, e, first, last, lo0, lo, size, w = self.stack.pop()
            which, _ = lookup(self.a, q, v, len(last))
            r0, r1, begin, n = next(cuts(size, most))
            row, edge = piece(self.a.by[which][1], lo, r0, r1, begin, n)
            self.work += len(edge)
            done = np.zeros(len(size), dtype=np.int64)
            done[r0:r1] = n
            if r1 < len(size) or (done < size).any():
                rest = slice(r1 - 1, None)  # rows before are done
                self.push(q, [x[rest] for x in v], [x[rest] for x in e], first[rest], last[rest], lo0[rest], (lo + done)[rest], (size - done)[rest], None if w is None else w[rest])
            row, edge = admitted(self.a, q, v, row, edge)
            if len(edge):
                grown = [x[row] for x in v] + [(self.a.s if end == "src" else self.a.d)[edge] for end, _ in step(q).new]
                yield from self.arrived(q, grown, [x[row] for x in e] + [edge] if self.keep else [], first[row], edge, None if w is None else w[row] * self.a.weight[edge])

    def left(self, most: int) -> Iterator[dict[str, np.ndarray]]:
        """The contexts on the stack as columns: node (the child's number), v0.., e0.., t_first, t_last, tie_last, skip, take, and weight if rows have one; runs longer than ``most`` are cut."""
        a = self.a
        for q, v, e, first, last, lo0, lo, size, w in self.stack:
            parts = -(-size // most)
            row = np.repeat(np.arange(len(size)), parts)
            part = np.arange(len(row)) - np.repeat(np.cumsum(parts) - parts, parts)
            out = {f"v{k}": a.ids[x[row]] for k, x in enumerate(v)} | {f"e{k}": a.edge_id[x[row]] for k, x in enumerate(e)} | ({} if w is None else {"weight": w[row]})
            skip = (lo - lo0)[row] + part * most
            take = np.minimum(size[row] - part * most, most)
            yield out | {"node": np.full(len(row), self.number[q]), "t_first": a.t[first[row]], "t_last": a.t[last[row]], "tie_last": a.tie[last[row]], "skip": skip, "take": take}

    def resume(self, node: int, rows: dict[str, np.ndarray]) -> None:
        """Contexts of one child, handed over by another search on the same edges."""
        a = self.a
        q = next(p for p, k in self.number.items() if k == node)
        v = [np.searchsorted(a.ids, rows[f"v{k}"]) for k in range(bound(q[:-1]))]
        which, key = lookup(a, q, v, len(rows["skip"]))
        place = a.place_of(rows["t_last"], rows["tie_last"])
        lo0, _ = a.spans(which, key, a.rank[place], a.last_rank(rows["t_first"] + self.delta))
        at = {x: k for k, x in enumerate(a.edge_id.tolist())} if self.keep else {}
        e = [np.array([at[x] for x in rows[f"e{k}"].tolist()], dtype=np.int64) for k in range(len(q) - 1)] if self.keep else []
        # Of the edges their ends and times are known, and the search reads no more of them: any first edge with the same will do.
        # The last one is read by its time only, until a next one takes its place.
        begun, (pairs, order) = a.rank[np.minimum(np.searchsorted(a.t, rows["t_first"], "left"), len(a.t) - 1)], a.by["pair"]
        first = order[np.minimum(np.searchsorted(pairs, (v[0] * a.vertices + v[0 if q[0][0] == q[0][1] else 1]) * a.span + begun, "left"), len(a.t) - 1)]
        last = e[-1] if self.keep else place
        self.push(q, v, e, e[0] if self.keep else first, last, lo0, lo0 + rows["skip"], rows["take"], rows.get("weight"))
