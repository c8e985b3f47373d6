"""Slabs of time: their borders, who owns what, and how hot ones are split."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Edges that one kernel task should get.
TARGET_EDGES = 500_000
#: Cells of the histogram of times that slabs are planned from.
CELLS = 16_384
#: Hot slabs with a number of replicas of their own.
MAX_HOT = 4_096


def numbers(values) -> Column:
    """An array constant: one literal that the optimizer folds, however long it is."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>")


def searched(values: tuple[int, ...], x: Column) -> Column:
    """How many of the sorted values are x at most: a binary search, one step a bit."""
    held, n = numbers(values), len(values)
    steps = F.array(*(F.lit(1 << b) for b in reversed(range(n.bit_length()))))
    return F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= n) & (F.get(held, at + s - 1) <= x), at + s).otherwise(at)).cast("long")


@dataclass(frozen=True)
class Grid:
    """Cells of one width; a cell has a first slab and how many equal slabs it is cut into (cells of one slab share its number)."""

    lo: int
    width: int
    first: tuple[int, ...]
    parts: tuple[int, ...]

    def index(self, t: Column) -> Column:
        width, last = F.lit(self.width).cast("long"), len(self.first) - 1
        off = F.greatest(F.least(t, F.lit(self.lo + self.width * (last + 1) - 1).cast("long")) - F.lit(self.lo).cast("long"), F.lit(0).cast("long"))
        cell = F.call_function("div", off, width).cast("int")
        if max(self.parts) == 1:
            return F.get(numbers(self.first), cell)
        inside = off - cell * width
        return F.get(numbers(self.first), cell) + F.call_function("div", inside, F.call_function("div", width + F.get(numbers(self.parts), cell) - 1, F.get(numbers(self.parts), cell)))


@dataclass(frozen=True)
class Slabs:
    """Half-open slabs: of one width (from 0), between borders or by a grid (there the first and last are open).

    ``replicas``: tasks that a slab's roots are dealt to; ``hot`` has (slab, replicas) where they differ.
    """

    delta: int
    width: int | None = None
    borders: tuple[int, ...] = ()
    replicas: int = 1
    grid: Grid | None = None
    hot: tuple[tuple[int, int], ...] = ()

    def index(self, t: Column) -> Column:
        if self.width:
            return _floor_div(t, self.width)
        if self.grid:
            return self.grid.index(t)
        return searched(self.borders, t) if self.borders else F.lit(0).cast("long")

    def replicas_of(self, slab: Column) -> Column:
        if not self.hot:
            return F.lit(self.replicas)
        slabs, many = zip(*sorted(self.hot), strict=True)
        at = searched(slabs, slab).cast("int") - 1
        return F.when((at >= 0) & (F.get(numbers(slabs), at) == slab), F.get(numbers(many), at).cast("int")).otherwise(F.lit(self.replicas))

    def assigned(self, edges: DataFrame) -> DataFrame:
        """Edges with slab, replica and owned: an edge goes to its own slab and to earlier ones whose halo holds it; hot slabs alone are copied to replicas."""
        t = F.col("t")
        out = edges.withColumn("own_slab", self.index(t)).withColumn("slab", F.explode(F.sequence(self.index(t - self.delta), F.col("own_slab"))))
        if self.replicas > 1 or self.hot:
            out = out.withColumn("of", self.replicas_of(F.col("slab"))).withColumn("replica", F.explode(F.sequence(F.lit(0), F.col("of") - 1)))
            mine = F.pmod(F.xxhash64("edge_id"), F.col("of")) == F.col("replica")
        else:
            out, mine = out.withColumn("of", F.lit(1)).withColumn("replica", F.lit(0)), F.lit(True)
        return out.withColumn("owned", (F.col("slab") == F.col("own_slab")) & mine).drop("own_slab", "of")


def _floor_div(t: Column, width: int) -> Column:
    """Floor division that stays in whole numbers, for negative times too."""
    w = F.lit(int(width)).cast("long")
    return F.call_function("div", t - F.pmod(t, w), w)


@dataclass(frozen=True)
class Histogram:
    """Edges by cell of time."""

    lo: int
    hi: int
    width: int
    counts: np.ndarray

    @property
    def n(self) -> int:
        return int(self.counts.sum())

    def widest_window(self, delta: int) -> int:
        """At least the edges of the fullest window (whole cells are counted)."""
        k = min(len(self.counts), -(-int(delta) // self.width) + 1)
        c = np.concatenate(([0], np.cumsum(self.counts)))
        return int((c[k:] - c[:-k]).max()) if len(self.counts) else 0


def histogram(edges: DataFrame, cells: int = CELLS) -> Histogram:
    """Two jobs and a bounded answer: span and size, then the edges of each cell."""
    r = edges.agg(F.count("*").alias("n"), F.min("t").alias("lo"), F.max("t").alias("hi")).collect()[0]
    if not r["n"]:
        return Histogram(0, 0, 1, np.zeros(0, dtype=np.int64))
    width = max(1, -(-(r["hi"] - r["lo"] + 1) // cells))
    counts = np.zeros((r["hi"] - r["lo"]) // width + 1, dtype=np.int64)
    for c in edges.groupBy(F.call_function("div", F.col("t") - F.lit(r["lo"]).cast("long"), F.lit(width).cast("long")).alias("c")).agg(F.count("*").alias("n")).collect():  # CELLS rows at most
        counts[c["c"]] = c["n"]
    return Histogram(r["lo"], r["hi"], width, counts)


def plan_slabs(edges: DataFrame, delta: int, target_edges: int = TARGET_EDGES, mode: str = "quantile", replicas: int = 1, seen: Histogram | None = None) -> Slabs:
    """Borders such that slabs get about ``target_edges`` edges, from a histogram of times.

    ``quantile`` joins cells up to the target and cuts fuller ones into equal parts; ``width`` cuts the span
    into equal widths.  Slabs narrower than the window still give right results, only with more copies, so
    they are kept at the window's width at least: a slab of more edges is a hot one, for ``salt_hot_slabs``.
    """
    h = seen or histogram(edges)
    slabs = max(1, -(-h.n // target_edges))
    if not h.n or slabs == 1:
        return Slabs(delta, None, (), replicas)
    if mode == "width":
        return Slabs(delta, max(int(delta), -(-(h.hi - h.lo + 1) // slabs), 1), (), replicas)
    first, parts, number, held, since = [], [], 0, 0, h.lo
    for c, n in enumerate(h.counts.tolist()):
        begin = h.lo + c * h.width
        cut = min(max(1, -(-n // target_edges)), max(1, h.width // int(delta)))
        if held and begin - since >= delta and (held + n > target_edges or cut > 1):
            number, held, since = number + 1, 0, begin
        if cut > 1 and not held:
            first.append(number)
            parts.append(cut)
            number, held, since = number + cut, 0, begin + h.width
        else:
            first.append(number)
            parts.append(1)
            held += n
    return Slabs(delta, None, (), replicas, Grid(h.lo, h.width, tuple(first), tuple(parts)))


#: Candidates that one kernel task should look at.
TASK_WORK = 50_000_000


def plan_by_work(edges: DataFrame, delta: int, candidates: float) -> Slabs:
    """Slabs of about TASK_WORK candidates; where slabs of a window's width have more, their roots are dealt to replicas."""
    h = histogram(edges)
    tasks = max(1, -(-h.n // TARGET_EDGES), int(candidates / TASK_WORK) + 1)
    slabs = max(1, min(tasks, (h.hi - h.lo) // int(delta)))
    return plan_slabs(edges, delta, max(1, -(-h.n // slabs)), replicas=min(64, -(-tasks // slabs)), seen=h)


def halo_factor(edges: DataFrame, slabs: Slabs) -> DataFrame:
    """One row: edges, copies and copies an edge (without replicas)."""
    copies = replace(slabs, replicas=1, hot=()).assigned(edges).agg(F.count("*").alias("copies"))
    return edges.agg(F.count("*").alias("edges")).crossJoin(copies).select("edges", "copies", F.round(F.col("copies") / F.col("edges"), 6).alias("halo_factor"))


def salt_hot_slabs(edges: DataFrame, slabs: Slabs, limit: int) -> Slabs:
    """The same slabs, each with as many replicas as it needs to stay under ``limit`` owned edges a task; the others are not copied."""
    owned = edges.groupBy(slabs.index(F.col("t")).alias("slab")).agg(F.count("*").alias("n")).where(F.col("n") > limit)
    rows = owned.orderBy(F.desc("n")).limit(MAX_HOT + 1).collect()
    hot = tuple((r["slab"], -(-r["n"] // limit)) for r in rows[:MAX_HOT])
    rest = -(-rows[MAX_HOT]["n"] // limit) if len(rows) > MAX_HOT else 1  # more hot slabs than a plan lists: all others get what the next one needs
    return replace(slabs, replicas=max(1, rest), hot=hot)


def work_slabs(edges: DataFrame, slabs: Slabs, limit: int) -> Slabs:
    """Replicas by candidate work: the out-edges that follow each edge in its slab, by degree, not the number of edges."""
    d = edges.select(slabs.index(F.col("t")).alias("slab"), "src", "dst")
    out = d.groupBy("slab", F.col("src").alias("dst")).agg(F.count("*").alias("o"))
    work = d.select("slab", "dst").join(out, ["slab", "dst"]).groupBy("slab").agg(F.sum("o").alias("n")).where(F.col("n") > limit)
    rows = work.orderBy(F.desc("n")).limit(MAX_HOT + 1).collect()
    rest = -(-rows[MAX_HOT]["n"] // limit) if len(rows) > MAX_HOT else 1
    return replace(slabs, replicas=max(1, rest), hot=tuple((r["slab"], -(-r["n"] // limit)) for r in rows[:MAX_HOT]))
