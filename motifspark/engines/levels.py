"""The levels engines: breadth first, frontiers of partial matches extended by joins.

``Frontiers`` has a frontier a prefix; one that several continuations (or a query and a
continuation) read is persisted, so that it is computed once.  ``Fused`` has a frontier a
depth: rows of all prefixes of that depth, each with its node's number, meet the edges in one
join, whichever end their next edge hangs on.  It makes as many joins as the longest motif has
edges after the first, and shuffles the edges once.

A time bucket of the window's width is part of the join keys: a row asks for two buckets, so
that a hub's whole history is never its list of candidates.
"""

from __future__ import annotations

import functools
import weakref
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from ..motif import Edge, pattern_text
from ..plan import Step, bound, step
from ..tree import PrefixTree

class Held(list):
    """Frames persisted for one result."""

    __hash__ = object.__hash__


#: Lists that collect the frames persisted inside holding(); the last one is the innermost.
_HOLDERS: list[Held] = [Held()]
#: All lists whose results are still there: Spark keeps one copy of equal frames, which goes with the last of them.
_LIVE: weakref.WeakSet[Held] = weakref.WeakSet(_HOLDERS)


def hold(df: DataFrame) -> DataFrame:
    """Persists on memory and disk; if it goes early, it is computed again."""
    _HOLDERS[-1].append(df.persist(StorageLevel.MEMORY_AND_DISK))
    return df


@contextmanager
def holding():
    """Frames persisted inside belong to the list that comes out: a result's own."""
    _HOLDERS.append(Held())
    _LIVE.add(_HOLDERS[-1])
    try:
        yield _HOLDERS[-1]
    finally:
        _HOLDERS.pop()


def release(result: DataFrame | None = None) -> None:
    """Lets the frames go that a result of mine() was computed from; without one, those that belong to no result."""
    held = _HOLDERS[0] if result is None else getattr(result, "held_frames", [])
    while held:
        frame = held.pop()
        try:
            if not any(frame.sameSemantics(f) for other in _LIVE if other is not held for f in other):
                frame.unpersist()
        except Exception:  # the session it belonged to has ended
            held.clear()


def edge_rows(edges: DataFrame, predicate: str | None) -> DataFrame:
    """The edges as a step sees them (renamed, so that self joins stay unambiguous)."""
    e = edges if predicate is None else edges.where(predicate)
    return e.select(F.col("edge_id").alias("g_id"), F.col("src").alias("g_src"), F.col("dst").alias("g_dst"), F.col("t").alias("g_t"), F.col("tie").alias("g_tie"))


def after(ties: str) -> Column:
    """The candidate edge comes later than the last one."""
    if ties == "strict":
        return F.col("g_t") > F.col("t_last")
    return (F.col("g_t") > F.col("t_last")) | ((F.col("g_t") == F.col("t_last")) & (F.col("g_tie") > F.col("tie_last")))


def within(delta: int) -> Column:
    return F.col("g_t") <= F.col("t_first") + F.lit(int(delta)).cast("long")


def unbound(s: Step, n: int) -> list[Column]:
    """New vertices differ from all bound ones, and from each other."""
    out = [F.col(f"g_{end}") != F.col(f"v{k}") for end, _ in s.new for k in range(n)]
    if len(s.new) == 2:
        out.append(F.col("g_src") != F.col("g_dst"))
    if s.kind == "loop":
        out.append(F.col("g_src") == F.col("g_dst"))
    return out


def conjunction(conditions: list[Column]) -> Column:
    out = conditions[0]
    for c in conditions[1:]:
        out = out & c
    return out


def root(edges: DataFrame, s: Step, enumerate_: bool, extra: str | None = None) -> DataFrame:
    """The frontier of a first edge.  ``extra`` anchors: only root edges that fulfil it."""
    e = edges if s.where is None else edges.where(s.where)
    e = e if extra is None else e.where(extra)
    e = e.where(F.col("src") == F.col("dst") if s.u == s.v else F.col("src") != F.col("dst"))
    ids = [F.col("edge_id").alias("e0")] if enumerate_ else []
    vs = [F.col("src").alias("v0")] if s.u == s.v else [F.col("src").alias("v0"), F.col("dst").alias("v1")]
    return e.select(*ids, *vs, F.col("t").alias("t_first"), F.col("t").alias("t_last"), F.col("tie").alias("tie_last"))


def _columns(depth: int, n: int, s: Step | None, enumerate_: bool) -> list[Column]:
    """The frontier's columns after the step at the depth, n vertices bound before it."""
    ids = [F.col(f"e{k}") for k in range(depth)] + [F.col("g_id").alias(f"e{depth}")] if enumerate_ else []
    new = [F.col(f"g_{end}").alias(f"v{x}") for end, x in (s.new if s else ())]
    return [*ids, *(F.col(f"v{k}") for k in range(n)), *new, F.col("t_first"), F.col("g_t").alias("t_last"), F.col("g_tie").alias("tie_last")]


def bucket(t: Column, width: int) -> Column:
    w = F.lit(max(1, int(width))).cast("long")
    return F.call_function("div", t - F.pmod(t, w), w)


def asked(delta: int, width: int) -> Column:
    """The buckets that can hold the next edge of a partial match."""
    return F.sequence(bucket(F.col("t_last"), width), bucket(F.col("t_first") + F.lit(int(delta)).cast("long"), width))


def expand(frontier: DataFrame, edges: DataFrame, prefix: tuple[Edge, ...], delta: int, ties: str, enumerate_: bool, bucketed: bool = True, hint: str | None = None, loose: bool = False) -> DataFrame:
    """The frontier of the prefix from that of the prefix before it.

    ``bucketed`` adds a time bucket of the window's width to the join keys: the frontier row
    asks two buckets at most, so a hub's whole history is never its candidate list.
    ``loose`` leaves out that new vertices must be new: all candidates that are looked at.
    """
    s, n, depth = step(prefix), bound(prefix[:-1]), len(prefix) - 1
    e = edge_rows(edges, s.where)
    on = [F.col(f"g_{end}") == F.col(f"v{x}") for end, x in s.anchors]
    if bucketed or s.kind == "free" or s.kind == "loop" and s.new:
        e = e.withColumn("g_bucket", bucket(F.col("g_t"), delta))
        frontier = frontier.withColumn("bucket", F.explode(asked(delta, delta)))
        on.append(F.col("g_bucket") == F.col("bucket"))
    if hint:
        e = e.hint(hint)
    return frontier.join(e, conjunction([*on, after(ties), within(delta), *([] if loose else unbound(s, n))])).select(_columns(depth, n, s, enumerate_))


class Frontiers:
    """Frontiers of all prefixes of a tree; shared ones are persisted."""

    def __init__(self, edges: DataFrame, tree: PrefixTree, delta: int, ties: str = "strict", enumerate_: bool = False, bucketed: bool = True, anchored: str | None = None, share: bool = True):
        self.edges, self.tree, self.delta, self.ties, self.enumerate_ = edges, tree, delta, ties, enumerate_
        self.bucketed, self.anchored, self.share = bucketed, anchored, share
        self.prefixes, self.queries = tree.prefixes(), tree.query_of()
        self.following: dict[tuple[Edge, ...], list[tuple[Edge, ...]]] = {p: [] for p in [(), *self.prefixes]}
        for p in self.prefixes:
            self.following[p[:-1]].append(p)
        self.frames: dict[tuple[Edge, ...], DataFrame] = {}
        self._grow(())

    def _grow(self, at: tuple[Edge, ...]) -> None:
        children = self.following[at]
        for p in children:
            f = root(self.edges, step(p), self.enumerate_, self.anchored) if not at else expand(self.frames[at], self.edges, p, self.delta, self.ties, self.enumerate_, self.bucketed)
            if self.share and len(self.following[p]) + (p in self.queries) > 1:
                f = hold(f)
            self.frames[p] = f
        for p in children:
            self._grow(p)

    def counts(self) -> DataFrame:
        """(motif, n) of the queries found in the tree; zeros are added by the caller."""
        parts = [f.select(F.lit(name).alias("motif")) for p, f in self.frames.items() if (name := self.queries.get(p))]
        return tallied(parts)

    def matches(self) -> DataFrame:
        """(motif, edge_path, t_first, t_last)."""
        out = None
        for p, f in self.frames.items():
            if name := self.queries.get(p):
                part = f.select(F.lit(name).alias("motif"), F.concat_ws("-", *(F.col(f"e{k}").cast("string") for k in range(len(p)))).alias("edge_path"), "t_first", "t_last")
                out = part if out is None else out.unionByName(part)
        return out

    def work(self) -> DataFrame:
        """(prefix, partials): rows of every frontier."""
        return tallied([f.select(F.lit(pattern_text(p)).alias("motif")) for p, f in self.frames.items()]).select(F.col("motif").alias("prefix"), F.col("n").alias("partials"))


#: How an edge is asked for: by its source, by its destination, or by time alone.
SRC, DST, ANY = 0, 1, 2


def asked_by(s: Step) -> int:
    return ANY if not s.anchors else SRC if s.anchors[0][0] == "src" else DST


def adjacency(edges: DataFrame, width: int, ends: set[int], predicates: list[str] = ()) -> DataFrame:
    """Edges as they are asked for: a row an edge and end, with the time bucket; the layout that Fused joins with."""
    rows = [F.struct(F.lit(k).alias("g_end"), key.cast("long").alias("g_key")) for k, key in ((SRC, F.col("src")), (DST, F.col("dst")), (ANY, F.lit(0))) if k in ends]
    flags = [F.coalesce(F.expr(w), F.lit(False)).alias(f"g_p{k}") for k, w in enumerate(predicates)]
    e = edges.select(F.col("edge_id").alias("g_id"), F.col("src").alias("g_src"), F.col("dst").alias("g_dst"), F.col("t").alias("g_t"), F.col("tie").alias("g_tie"), bucket(F.col("t"), width).alias("g_bucket"), *flags, F.explode(F.array(*rows)).alias("a"))
    return e.select("a.g_end", "a.g_key", *(c for c in e.columns if c != "a"))


class Fused:
    """Frontiers by depth; ``layout``: a stored adjacency (and the width of its buckets), read instead of dealing the edges out."""

    def __init__(self, edges: DataFrame, tree: PrefixTree, delta: int, ties: str = "strict", enumerate_: bool = False, anchored: str | None = None, layout: tuple[DataFrame, int] | None = None):
        self.delta, self.ties, self.enumerate_ = int(delta), ties, enumerate_
        self.queries = tree.query_of()
        self.prefixes = tree.prefixes()
        self.number = {p: k for k, p in enumerate(self.prefixes)}
        self.wheres = sorted({w for p in self.prefixes for _, _, w in p if w})
        ends = {asked_by(step(p)) for p in self.prefixes if len(p) > 1}
        if layout and (self.wheres or ANY in ends):
            raise ValueError("a stored layout has no predicates and is not asked by time alone")
        self.adjacency, self.width = layout or (adjacency(edges, delta, ends, self.wheres) if ends else None, self.delta)
        deepest = max(map(len, self.prefixes), default=0)
        self.frames = [self._roots(edges, anchored)]
        for depth in range(1, deepest):
            frame = self.frames[-1]
            if any(len(p) == depth for p in self.queries):
                frame = self.frames[-1] = hold(frame)
            self.frames.append(self._next(frame, depth))

    def _at(self, depth: int) -> list[tuple[Edge, ...]]:
        return [p for p in self.prefixes if len(p) == depth]

    def _roots(self, edges: DataFrame, anchored: str | None) -> DataFrame:
        e = edges if anchored is None else edges.where(anchored)
        cases, loops = [], False
        for p in self._at(1):
            s = step(p)
            loops |= s.u == s.v
            fits = F.col("src") == F.col("dst") if s.u == s.v else F.col("src") != F.col("dst")
            cases.append(F.when(fits & F.expr(s.where) if s.where else fits, F.lit(self.number[p])))
        ids = [F.col("edge_id").alias("e0")] if self.enumerate_ else []
        v1 = F.when(F.col("src") != F.col("dst"), F.col("dst")) if loops else F.col("dst")
        every = F.explode(F.array_compact(F.array(*cases))) if len(cases) > 1 else cases[0]
        out = e.select(every.alias("node"), *ids, F.col("src").alias("v0"), v1.alias("v1"), F.col("t").alias("t_first"), F.col("t").alias("t_last"), F.col("tie").alias("tie_last"))
        return out.where("node is not null")

    def _next(self, frame: DataFrame, depth: int) -> DataFrame:
        nexts = self._at(depth + 1)
        have = [c for c in frame.columns if c.startswith("v")]
        asks, checks, binds = [], [], {}
        for q in nexts:
            s, n, k = step(q), bound(q[:-1]), F.lit(self.number[q])
            end = asked_by(s)
            key = F.lit(0).cast("long") if end == ANY else F.col(f"v{s.anchors[0][1]}")
            asks.append(F.when(F.col("node") == self.number[q[:-1]], F.struct(k.alias("child"), F.lit(end).alias("end"), key.alias("key"))))
            c = [F.col(f"g_{side}") == F.col(f"v{x}") for side, x in s.anchors[1:]] + unbound(s, n)
            if s.where:
                c.append(F.col(f"g_p{self.wheres.index(s.where)}"))
            checks.append((F.col("child") == k, conjunction(c) if c else F.lit(True)))
            for side, x in s.new:
                binds.setdefault(f"v{x}", []).append((F.col("child") == k, F.col(f"g_{side}")))
        left = frame.select("*", F.explode(F.array_compact(F.array(*asks))).alias("ask")).select(*(c for c in frame.columns if c != "node"), "ask.*")
        left = left.withColumn("bucket", F.explode(asked(self.delta, self.width)))
        fits = functools.reduce(lambda acc, x: acc.when(*x), checks[1:], F.when(*checks[0])) if len(checks) > 1 else checks[0][1]
        on = [F.col("g_end") == F.col("end"), F.col("g_key") == F.col("key"), F.col("g_bucket") == F.col("bucket"), after(self.ties), within(self.delta), fits]
        joined = left.join(self.adjacency, conjunction(on))
        vs = []
        for name in sorted({*have, *binds}, key=lambda c: int(c[1:])):
            old = F.col(name) if name in have else F.lit(None).cast("long")
            vs.append((functools.reduce(lambda acc, x: acc.when(*x), binds[name][1:], F.when(*binds[name][0])).otherwise(old) if name in binds else old).alias(name))
        ids = [F.col(f"e{k}") for k in range(depth)] + [F.col("g_id").alias(f"e{depth}")] if self.enumerate_ else []
        return joined.select(F.col("child").alias("node"), *ids, *vs, "t_first", F.col("g_t").alias("t_last"), F.col("g_tie").alias("tie_last"))

    def _named(self, frame: DataFrame, depth: int, names: dict[tuple[Edge, ...], str]) -> DataFrame | None:
        here = [(F.col("node") == self.number[p], F.lit(n)) for p, n in names.items() if len(p) == depth]
        if not here:
            return None
        motif = functools.reduce(lambda acc, x: acc.when(*x), here[1:], F.when(*here[0]))
        return frame.withColumn("motif", motif).where("motif is not null")

    def _tally(self, names: dict[tuple[Edge, ...], str]) -> DataFrame:
        parts = [self._named(f, d, names) for d, f in enumerate(self.frames, 1)]
        return tallied([p for p in parts if p is not None])

    def counts(self) -> DataFrame:
        return self._tally(self.queries)

    def work(self) -> DataFrame:
        return self._tally({p: pattern_text(p) for p in self.prefixes}).select(F.col("motif").alias("prefix"), F.col("n").alias("partials"))

    def matches(self) -> DataFrame:
        parts = []
        for d, f in enumerate(self.frames, 1):
            named = self._named(f, d, self.queries)
            if named is not None:
                parts.append(named.select("motif", F.concat_ws("-", *(F.col(f"e{k}").cast("string") for k in range(d))).alias("edge_path"), "t_first", "t_last"))
        return functools.reduce(DataFrame.unionByName, parts)


def expected(edges: DataFrame, tree: PrefixTree, delta: int) -> tuple[float, float]:
    """About how many rows frontiers would shuffle, and how many candidates would be looked at; one job without a shuffle of edges.

    From the edges of a window over the vertices that send or receive: an estimate for the plan only, results do not
    depend on it.
    """
    r = edges.agg(F.count("*").alias("n"), F.min("t").alias("lo"), F.max("t").alias("hi"), F.approx_count_distinct("src").alias("s"), F.approx_count_distinct("dst").alias("d")).first()
    if not r["n"]:
        return 0.0, 0.0
    window = r["n"] * min(1.0, int(delta) / max(1, r["hi"] - r["lo"]))
    each = {"root": float(r["n"]), "out": window / max(1, r["s"]), "in": window / max(1, r["d"]), "closed": window / max(1, r["s"] * r["d"]), "loop": window / max(1, r["s"]), "free": window}
    rows: dict[tuple[Edge, ...], float] = {(): 1.0}
    shuffled = looked = 0.0
    prefixes = tree.prefixes()
    inner = {p[:-1] for p in prefixes}
    for p in prefixes:
        rows[p] = rows[p[:-1]] * each[step(p).kind]
        shuffled += rows[p] if p in inner else 0
        looked += rows[p] if len(p) > 1 else 0
    return shuffled, looked


def tallied(parts: list[DataFrame]) -> DataFrame:
    """Each part is counted before the union, so only counts are shuffled."""
    out = None
    for part in parts:
        c = part.groupBy("motif").agg(F.count("*").alias("n"))
        out = c if out is None else out.unionByName(c)
    return out
