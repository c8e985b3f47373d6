"""Cost and accuracy measures."""

from __future__ import annotations

import statistics
import threading
import time
from collections import Counter
from collections.abc import Callable
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import balance
from .api import MineSpec, mine, source_edges, window
from .engines import slabs as slab_engine
from .engines.levels import Frontiers, Fused, expand, expected, hold, tallied
from .graph import TemporalGraph
from .motif import Motif, pattern_text
from .tree import PrefixTree, similarity_by_prefix


def work(spec: MineSpec, group: str = "group") -> DataFrame:
    """(group_name, prefix, partials): partial matches of every distinct prefix, the engines' common unit of work."""
    tree = PrefixTree.build(spec.motifs)
    f = Fused(hold(source_edges(spec)), tree, window(spec.delta), spec.ties)
    names = mineable(spec, [(pattern_text(p),) for p in tree.prefixes()])
    return names.join(F.broadcast(f.work()), "prefix", "left").select(F.lit(group).alias("group_name"), "prefix", F.coalesce("partials", F.lit(0)).cast("long").alias("partials"))


def mineable(spec: MineSpec, rows: list[tuple]) -> DataFrame:
    return spec.graph.edges.sparkSession.createDataFrame(rows, "prefix string")


def work_ratio(spec: MineSpec, group: str = "group") -> DataFrame:
    """One row: partial matches mined one by one, mined together, and their ratio."""
    tree = PrefixTree.build(spec.motifs)
    weight: dict[str, int] = {}
    for key in tree.query_of():
        for k in range(1, len(key) + 1):
            weight[pattern_text(key[:k])] = weight.get(pattern_text(key[:k]), 0) + 1
    w = spec.graph.edges.sparkSession.createDataFrame(list(weight.items()), "prefix string, weight bigint")
    out = work(spec, group).join(F.broadcast(w), "prefix").groupBy("group_name").agg(F.sum(F.col("weight") * F.col("partials")).alias("independent"), F.sum("partials").alias("shared"))
    return out.withColumn("ratio", F.round(F.col("independent") / F.col("shared"), 4))


def work_ratios(graph: TemporalGraph, groups: dict[str, list[Motif]], delta: int) -> DataFrame:
    """(group_name, independent, shared): ``work_ratio`` of several groups from one search of the graph, every prefix counted once.

    Slabs are searched depth first, so that no frontier is shuffled or kept.
    """
    spark = graph.edges.sparkSession
    rows = []
    for name, motifs in groups.items():
        keys = list(PrefixTree.build(motifs).query_of())
        weight = Counter(pattern_text(key[:k]) for key in keys for k in range(1, len(key) + 1))
        rows += [(name, prefix, n) for prefix, n in weight.items()]
    every = PrefixTree.build([Motif.parse(p, p) for p in sorted({p for _, p, _ in rows})])
    edges = hold(graph.edges.select("edge_id", "src", "dst", "t", "tie"))
    cut = balance.plan_by_work(edges, delta, expected(edges, every, delta)[1])
    found = slab_engine.run(edges, every, delta, cut).toDF("prefix", "partials")
    said = spark.createDataFrame(rows, "group_name string, prefix string, weight bigint").join(F.broadcast(found), "prefix", "left").withColumn("partials", F.coalesce("partials", F.lit(0)))
    return said.groupBy("group_name").agg(F.sum(F.col("weight") * F.col("partials")).alias("independent"), F.sum("partials").alias("shared"))


def density(spec: MineSpec) -> DataFrame:
    """(motif, n, density): matches an edge."""
    edges = spec.graph.edges.agg(F.count("*").alias("edges"))
    return mine(spec).crossJoin(F.broadcast(edges)).select("motif", "n", F.round(F.col("n") / F.col("edges"), 6).alias("density"))


def similarities(groups: dict[str, list]) -> list[tuple[str, float, float]]:
    return [(name, round(PrefixTree.build(ms).similarity(), 4), round(similarity_by_prefix(ms), 4)) for name, ms in groups.items()]


def geomean(df: DataFrame, column: str, by: list[str]) -> DataFrame:
    return df.groupBy(*by).agg(F.round(F.exp(F.avg(F.log(column))), 6).alias("geomean"))


def time_weighted(df: DataFrame, seconds: str, metric: str, by: list[str]) -> DataFrame:
    """A metric's mean over runs, weighted by how long each ran."""
    return df.groupBy(*by).agg(F.round(F.sum(F.col(seconds) * F.col(metric)) / F.sum(seconds), 6).alias(metric))


def probes(spec: MineSpec, group: str = "group") -> DataFrame:
    """(group_name, prefix, probes): candidate edges looked at for each distinct prefix, before new vertices are compared."""
    edges, delta = hold(source_edges(spec)), window(spec.delta)
    f = Frontiers(edges, PrefixTree.build(spec.motifs), delta, spec.ties)
    parts = [expand(f.frames[p[:-1]], edges, p, delta, spec.ties, False, loose=True).select(F.lit(pattern_text(p)).alias("motif")) for p in f.prefixes if len(p) > 1]
    names = mineable(spec, [(pattern_text(p),) for p in f.prefixes if len(p) > 1])
    found = tallied(parts).select(F.col("motif").alias("prefix"), F.col("n").alias("probes"))
    return names.join(F.broadcast(found), "prefix", "left").select(F.lit(group).alias("group_name"), "prefix", F.coalesce("probes", F.lit(0)).cast("long").alias("probes"))


def copies(edges: DataFrame, plans: dict[str, tuple]) -> DataFrame:
    """(plan, edges, copies): what each way of balancing adds to the one shuffle; plans: name -> (Slabs, tasks a slab and replica)."""
    out = None
    for name, (slabs, branches) in plans.items():
        row = slabs.assigned(edges).agg((F.count("*") * branches).cast("long").alias("copies")).select(F.lit(name).alias("plan"), "copies")
        out = row if out is None else out.unionByName(row)
    return out.crossJoin(F.broadcast(edges.agg(F.count("*").alias("edges")))).select("plan", "edges", "copies")


def listed_and_counted(spec: MineSpec) -> DataFrame:
    """(motif, listed, counted): matches as rows, and the same matches by counters kept in the kernels' state; they must agree."""
    from dataclasses import replace

    listed = mine(replace(spec, mode="enumerate")).groupBy("motif").agg(F.count("*").alias("listed"))
    return mine(spec).withColumnRenamed("n", "counted").join(F.broadcast(listed), "motif", "left").select("motif", F.coalesce("listed", F.lit(0)).cast("long").alias("listed"), "counted")


class Run(NamedTuple):
    """Seconds, and what the stages that ran say: bytes shuffled and spilled, skew (longest task over the median one,
    of the stage that took longest), busy (share of the cores' time that tasks ran).  seconds is None if the limit ended it.
    """

    seconds: float | None
    shuffle_mb: float = 0.0
    spill_mb: float = 0.0
    skew: float = 1.0
    busy: float = 0.0


def observed(spark: SparkSession, build: Callable[[], DataFrame], limit: float | None = None) -> Run:
    """Runs what ``build`` makes, writing the result nowhere; beyond the limit its jobs are cancelled."""
    sc = spark.sparkContext
    store, jvm = sc._jsc.sc().statusStore(), sc._jvm
    last = max((s.stageId() for s in _stages(sc, store, jvm)), default=-1)
    group, late = f"observed-{time.monotonic_ns()}", threading.Event()
    sc.setJobGroup(group, "observed", True)

    def stop() -> None:
        late.set()
        sc.cancelJobGroup(group)

    timer = threading.Timer(limit, stop) if limit else None
    if timer:
        timer.start()
    t = time.perf_counter()
    try:
        build().write.format("noop").mode("overwrite").save()
    except Exception:
        if not late.is_set():
            raise
    finally:
        seconds = time.perf_counter() - t
        if timer:
            timer.cancel()
        sc.setLocalProperty("spark.jobGroup.id", None)
    if late.is_set():
        return Run(None)
    mine_ = [s for s in _stages(sc, store, jvm) if s.stageId() > last]
    total = sum(s.executorRunTime() for s in mine_) / 1000
    skew = 1.0
    if mine_:
        slowest = max(mine_, key=lambda s: s.executorRunTime())
        tasks = store.taskList(slowest.stageId(), slowest.attemptId(), 1_000)
        times = [x.get().executorRunTime() for i in range(tasks.size()) if (x := tasks.apply(i).taskMetrics()).isDefined()]
        if len(times) > 1:
            skew = max(times) / max(1.0, statistics.median(times))
    return Run(seconds, sum(s.shuffleWriteBytes() for s in mine_) / 1e6, sum(s.memoryBytesSpilled() for s in mine_) / 1e6, round(skew, 2), round(total / max(1e-9, seconds * sc.defaultParallelism), 3))


def _stages(sc, store, jvm) -> list:
    none = jvm.java.util.ArrayList()
    found = store.stageList(none, False, False, sc._gateway.new_array(jvm.double, 0), none)
    return [found.apply(i) for i in range(found.size())]


def persisted_mb(spark: SparkSession) -> float:
    """Memory and disk that persisted frames take."""
    return sum(r.memSize() + r.diskSize() for r in spark.sparkContext._jsc.sc().getRDDStorageInfo()) / 1e6


def exchanges(df: DataFrame) -> int:
    """Shuffles of the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return text.count("Exchange hashpartitioning") + text.count("Exchange SinglePartition")
