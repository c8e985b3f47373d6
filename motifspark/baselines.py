"""What co-mining is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .api import MineSpec, mine, window
from .balance import Slabs
from .engines import slabs as slab_engine
from .engines.levels import conjunction, hold
from .motif import Motif
from .plan import bound
from .tree import PrefixTree


def sql_join(edges: DataFrame, motif: Motif, delta: int) -> DataFrame:
    """One flat self join with all conditions in WHERE: (motif, n)."""
    m = motif.canonical()
    names = [f"e{k}" for k in range(len(m))]
    at: dict[int, str] = {}
    where = []
    for k, (u, v) in enumerate(m.edges):
        for end, x in (("src", u), ("dst", v)):
            here = f"e{k}.{end}"
            if x in at:
                where.append(f"{here} = {at[x]}")
            else:
                where += [f"{here} <> {y}" for y in at.values()]
                at[x] = here
        if k:
            where += [f"e{k}.t > e{k - 1}.t", f"e{k}.t <= e0.t + {int(delta)}"]
    text = f"SELECT '{motif.name}' AS motif, count(*) AS n FROM {', '.join('{edges} ' + n for n in names)} WHERE {' AND '.join(where)}"
    return edges.sparkSession.sql(text, edges=edges)


def static_then_filter(edges: DataFrame, motif: Motif, delta: int) -> DataFrame:
    """Matches on distinct (src, dst) pairs first, then their timed edges, then the time conditions: (motif, n)."""
    m = motif.canonical()
    pairs = hold(edges.select("src", "dst").distinct())
    found, have = None, 0
    for k, (u, v) in enumerate(m.edges):
        e = pairs.select(F.col("src").alias("g_src"), F.col("dst").alias("g_dst"))
        if found is None:
            found = e.where("g_src <> g_dst" if u != v else "g_src = g_dst").select(F.col("g_src").alias("v0"), *([F.col("g_dst").alias("v1")] if u != v else []))
            have = 1 + (u != v)
            continue
        on = [F.col(f"g_{end}") == F.col(f"v{x}") for end, x in (("src", u), ("dst", v)) if x < have]
        new = [(end, x) for end, x in (("src", u), ("dst", v)) if x >= have]
        on += [F.col(f"g_{end}") != F.col(f"v{y}") for end, _ in new for y in range(have)]
        found = found.join(e, conjunction(on)).select(*(f"v{y}" for y in range(have)), *(F.col(f"g_{end}").alias(f"v{x}") for end, x in new))
        have = bound(tuple((a, b, None) for a, b in m.edges[: k + 1]))
    timed = found
    for k, (u, v) in enumerate(m.edges):
        e = edges.select(F.col("src").alias("x_src"), F.col("dst").alias("x_dst"), F.col("t").alias(f"t{k}"))
        on = [F.col("x_src") == F.col(f"v{u}"), F.col("x_dst") == F.col(f"v{v}")]
        if k:
            on += [F.col(f"t{k}") > F.col(f"t{k - 1}"), F.col(f"t{k}") <= F.col("t0") + int(delta)]
        timed = timed.join(e, conjunction(on)).drop("x_src", "x_dst")
    return timed.agg(F.count("*").alias("n")).select(F.lit(motif.name).alias("motif"), "n")


def unordered(edges: DataFrame, delta: int) -> DataFrame:
    """(kind, n): 3-cycles whose edges lie in one window in any order, and those of them in motif order.

    A static rewriting counts the first; only the time filter gives the second.
    """
    e = lambda k: edges.where("src <> dst").select(*(F.col(c).alias(f"{c}{k}") for c in ("edge_id", "src", "dst", "t")))
    j = e(0).join(e(1), F.col("src1") == F.col("dst0")).where((F.col("dst1") != F.col("src0")) & (F.abs(F.col("t1") - F.col("t0")) <= delta))
    j = j.join(e(2), (F.col("src2") == F.col("dst1")) & (F.col("dst2") == F.col("src0")))
    j = j.where(F.greatest("t0", "t1", "t2") - F.least("t0", "t1", "t2") <= delta)
    both = j.agg(F.count("*").alias("any_order"), F.sum(((F.col("t0") < F.col("t1")) & (F.col("t1") < F.col("t2"))).cast("long")).alias("in_order"))
    return both.select(F.expr("stack(2, 'any_order', any_order, 'in_order', coalesce(in_order, 0L)) AS (kind, n)"))


def scan_sharing(spec: MineSpec) -> DataFrame:
    """Only the scan of the edges is shared: every motif has its own frontiers over one persisted edge table."""
    from dataclasses import replace

    shared = replace(spec.graph, edges=hold(spec.graph.edges))
    return mine(replace(spec, graph=shared, independent=True, engine="levels"))


def approximate(spec: MineSpec, width: int, every: int = 2) -> DataFrame:
    """A contrast only: slabs of the width with number divisible by ``every`` are mined, counts scaled up."""
    delta = window(spec.delta)
    tree = PrefixTree.build(spec.motifs)
    cut = Slabs(delta, width)
    edges = spec.graph.edges
    w = int(width)
    kept = edges.where(F.pmod(F.expr(f"t div {w}"), F.lit(every)) == 0).select("edge_id").withColumn("anchor", F.lit(True))
    marked = edges.join(kept, "edge_id", "left").withColumn("anchor", F.coalesce("anchor", F.lit(False)))
    out = slab_engine.run(marked, tree, delta, cut, anchored="anchor")
    from .api import with_zeros

    return with_zeros(out.select("motif", (F.col("n") * every).cast("long").alias("n")), tree)
