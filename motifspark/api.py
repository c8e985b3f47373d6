"""mine(): one call for a group of motifs, a window, a mode and an engine."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import balance, heuristic
from .engines import epochs, sqlgen
from .engines import slabs as slab_engine
from .engines.levels import Frontiers, Fused, expected, hold, holding
from .graph import TemporalGraph
from .motif import Motif
from .tree import PrefixTree

UNITS = {"us": 1, "ms": 1_000, "s": 1_000_000, "min": 60_000_000, "h": 3_600_000_000, "d": 86_400_000_000}


def window(delta: int | str) -> int:
    """Microseconds of ``"12 h"``, ``"1 day"``, or of a number as it is; must be positive."""
    if isinstance(delta, str):
        m = re.fullmatch(r"\s*(\d+(?:\.\d+)?)\s*(us|ms|s|sec\w*|min\w*|h|hour\w*|d|day\w*)\s*", delta)
        if not m:
            raise ValueError(f"can't read the window {delta!r}")
        unit = next(u for u in ("us", "ms", "min", "s", "h", "d") if m[2].startswith(u))
        delta = round(float(m[1]) * UNITS[unit])
    if delta <= 0:
        raise ValueError("the window must be positive")
    return int(delta)


@dataclass(frozen=True)
class MineSpec:
    """engine: auto, levels, fused, slabs, hybrid or sql.  mode: count or enumerate.  ties: strict or sequence.

    deltas: windows of single motifs; the group is mined at the widest one.
    anchored: a predicate on first edges.  independent: every motif by itself (the baseline).
    """

    graph: TemporalGraph
    motifs: list[Motif]
    delta: int | str
    mode: str = "count"
    engine: str = "auto"
    ties: str = "strict"
    deltas: dict[str, int] = field(default_factory=dict)
    anchored: str | None = None
    independent: bool = False
    bucketed: bool = True
    kernel: str = "special"
    target_edges: int = balance.TARGET_EDGES
    slab_mode: str = "quantile"
    slab_width: int | None = None
    replicas: int = 1
    split_siblings: int = 0
    hot_edges: int | None = None
    hot_work: int | None = None
    budget: int = epochs.BUDGET
    least_work: int = epochs.LEAST_WORK
    offload: str = "all"
    layout: tuple[str, int] | None = None
    max_per_motif: int | None = None
    prune: bool = False
    cut: balance.Slabs | None = None
    resources: str = "plenty"
    window_choice: tuple[int, ...] = ()


#: Edges in a window from which one task can't hold a slab any more; graphs of fewer edges need no cutting.
EDGES_A_WINDOW, FEW_EDGES = 5_000_000, 20_000


#: Rows that frontiers may be expected to shuffle, and candidates that joins may look at; beyond either no frontier is made.
FRONTIER_ROWS, CANDIDATES = 100_000_000, 1_000_000_000


def depth_first(spec: MineSpec, tree: PrefixTree, edges: DataFrame) -> DataFrame | None:
    """Where frontiers would be too large: the same result from tasks that search slabs of time and hand over no partial match.

    Counts in strict order follow equal edges once.  None where frontiers stay within bounds.
    """
    delta = window(spec.delta)
    if len(tree.prefixes()) < 2:
        return None
    shuffled, looked = expected(edges, tree, delta)
    if shuffled <= FRONTIER_ROWS and looked <= CANDIDATES:
        return None
    if spec.mode == "count" and spec.ties == "strict":
        rows = hold(slab_engine.alike(edges, tree, spec.anchored))
        return slab_engine.run_alike(rows, tree, delta, balance.plan_by_work(rows, delta, expected(rows, tree, delta)[1]))
    return slab_engine.run(edges, tree, delta, balance.plan_by_work(edges, delta, looked), spec.mode, spec.ties, anchored=spec.anchored)


def pick_engine(spec: MineSpec, seen: balance.Histogram | None = None) -> str:
    """Slabs while the fullest window's edges fit a task, else the fused levels; small graphs need no cutting at all."""
    h = seen or balance.histogram(spec.graph.edges)
    if h.n <= FEW_EDGES:
        return "fused"
    return "slabs" if h.widest_window(window(spec.delta)) <= EDGES_A_WINDOW else "fused"


def with_zeros(counts: DataFrame, tree: PrefixTree) -> DataFrame:
    """One row a name of the group, aliases too; motifs not found count 0."""
    spark = counts.sparkSession
    names = spark.createDataFrame([(n, tree.aliases.get(n, n)) for n in tree.queries], "motif string, found string")
    return names.join(F.broadcast(counts.withColumnRenamed("motif", "found")), "found", "left").select("motif", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def with_aliases(matches: DataFrame, tree: PrefixTree) -> DataFrame:
    if not tree.aliases:
        return matches
    names = matches.sparkSession.createDataFrame([(n, tree.aliases.get(n, n)) for n in tree.queries], "name string, motif string")
    return matches.join(F.broadcast(names), "motif").drop("motif").withColumnRenamed("name", "motif").select("motif", "edge_path", "t_first", "t_last")


def mine(spec: MineSpec) -> DataFrame:
    """Counts (motif, n) with zeros, or matches (motif, edge_path, t_first, t_last).

    Frames persisted for the result are its own (``held_frames``); engines.levels.release(result) lets them go.
    """
    with holding() as held:
        out = _result(spec)
    out.held_frames = held
    return out


def _result(spec: MineSpec) -> DataFrame:
    if spec.deltas:
        return _mixed(spec)
    tree = PrefixTree.build(spec.motifs)
    if spec.engine == "auto":
        spec = followed(spec, tree)
    if spec.independent:
        spec = planned(spec)
        out = None
        seen = set(tree.aliases)
        for m in spec.motifs:
            if m.name not in seen:
                part = _mine(spec, PrefixTree.build([m]))
                out = part if out is None else out.unionByName(part)
    else:
        out = _mine(spec, tree.prune_bipartite() if spec.prune else tree)
    return finished(spec, out, tree)


def planned(spec: MineSpec) -> MineSpec:
    """The spec with its slabs planned, so that motifs mined one by one share a plan."""
    if spec.engine not in ("slabs", "hybrid") or spec.cut is not None:
        return spec
    return replace(spec, cut=slabs_of(spec, source_edges(spec)))


def slabs_of(spec: MineSpec, edges: DataFrame) -> balance.Slabs:
    if spec.cut is not None:
        return spec.cut
    delta = window(spec.delta)
    if spec.slab_width:
        cut = balance.Slabs(delta, spec.slab_width, (), spec.replicas)
    else:
        cut = balance.plan_slabs(edges, delta, spec.target_edges, spec.slab_mode, spec.replicas)
    if spec.hot_edges:
        cut = balance.salt_hot_slabs(edges, cut, spec.hot_edges)
    if spec.hot_work:
        cut = balance.work_slabs(edges, cut, spec.hot_work)
    return cut


def followed(spec: MineSpec, tree: PrefixTree) -> MineSpec:
    """The spec as the heuristic and the graph's profile would have it.

    A bipartite graph's tree is pruned and mined together; motifs that share too little are mined by
    themselves where resources are scarce; of the windows a caller can live with the smallest is taken.
    """
    h = balance.histogram(spec.graph.edges)
    advice = heuristic.advise(bool(spec.graph.sides), tree.similarity(), spec.resources)
    if spec.window_choice and advice.prefer_smaller_delta:
        spec = replace(spec, delta=min(map(window, spec.window_choice)))
    cut = balance.plan_slabs(spec.graph.edges, window(spec.delta), spec.target_edges, spec.slab_mode, spec.replicas, h)
    return replace(spec, engine=pick_engine(spec, h), independent=spec.independent or not advice.co_mine, prune=spec.prune or bool(spec.graph.sides), cut=spec.cut or cut)


def finished(spec: MineSpec, out: DataFrame, tree: PrefixTree) -> DataFrame:
    if spec.mode == "count":
        return with_zeros(out, tree)
    out = with_aliases(out, tree)
    if spec.max_per_motif:
        from pyspark.sql import Window as W

        rank = F.row_number().over(W.partitionBy("motif").orderBy("t_first", "t_last", "edge_path"))
        out = out.withColumn("_r", rank).where(F.col("_r") <= spec.max_per_motif).drop("_r")
    return out


def source_edges(spec: MineSpec) -> DataFrame:
    needs_labels = any(w and ("slabel" in w or "dlabel" in w) for m in spec.motifs for w in m.where)
    return spec.graph.labelled() if needs_labels else spec.graph.edges


def _mine(spec: MineSpec, tree: PrefixTree) -> DataFrame:
    delta = window(spec.delta)
    if not tree.query_of():
        kind = "motif string, n bigint" if spec.mode == "count" else slab_engine.MATCHES
        return spec.graph.edges.sparkSession.createDataFrame([], kind)
    engine = pick_engine(spec) if spec.engine == "auto" else spec.engine
    edges = source_edges(spec)
    enumerate_ = spec.mode != "count"
    if engine == "levels":
        edges = hold(edges) if len(tree.prefixes()) > 1 else edges
        if (out := depth_first(spec, tree, edges)) is not None:
            return out
        f = Frontiers(edges, tree, delta, spec.ties, enumerate_, spec.bucketed, spec.anchored)
        return f.matches() if enumerate_ else f.counts()
    if engine == "fused":
        layout = (edges.sparkSession.table(spec.layout[0]), spec.layout[1]) if spec.layout else None
        f = Fused(edges, tree, delta, spec.ties, enumerate_, spec.anchored, layout)
        return f.matches() if enumerate_ else f.counts()
    if engine == "slabs":
        return slab_engine.run(edges, tree, delta, slabs_of(spec, edges), spec.mode, spec.ties, spec.kernel, spec.split_siblings, spec.anchored)
    if engine == "hybrid":
        return epochs.run(edges, tree, delta, slabs_of(spec, edges), spec.mode, spec.ties, spec.anchored, spec.budget, spec.least_work, spec.split_siblings > 0, spec.offload).found
    if engine == "sql":
        if spec.anchored:
            raise ValueError("the sql engine has no anchors")
        out = depth_first(spec, tree, edges)
        return sqlgen.run(edges, tree, delta, spec.ties, spec.mode) if out is None else out
    raise ValueError(f"no engine {engine!r}")


def _mixed(spec: MineSpec) -> DataFrame:
    """Windows nest: mined at the widest one, each motif's matches are then held to its own."""
    widest = max([window(spec.delta), *map(window, spec.deltas.values())])
    every = _result(replace(spec, delta=widest, mode="enumerate", deltas={}, max_per_motif=None))
    own = {m.name: window(spec.deltas.get(m.name, spec.delta)) for m in spec.motifs}
    table = every.sparkSession.createDataFrame(list(own.items()), "motif string, own bigint")
    kept = every.join(F.broadcast(table), "motif").where("t_last - t_first <= own").select("motif", "edge_path", "t_first", "t_last")
    if spec.mode != "count":
        return kept
    return with_zeros(kept.groupBy("motif").agg(F.count("*").alias("n")), PrefixTree(PrefixTree.build(spec.motifs).root, [m.name for m in spec.motifs], {}))
