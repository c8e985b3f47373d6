"""The hybrid engine: epochs of depth-first search with the work dealt out anew between them.

In each epoch a task searches its slab until its budget of candidate edges is used up.  What
then lies on its stack is handed over as rows: contexts, one for each sibling on each level up
to the root, each with a run of candidates; long runs are cut.  Between epochs contexts are
dealt to as many owners a slab as their work needs, and only owners that were dealt some get
their slab's edges again.  Where a slab's edges are many times
the budget, the budget grows with them, so that copies stay a small part of the work; after
some epochs it doubles from one to the next.  Every candidate lies in one run and
every run has one owner, so nothing is found twice.

Contexts and results of an epoch are written to the shared folder: an executor that is lost
costs its tasks of one epoch, and no lineage grows.  What an epoch shuffled is let go when it is
written, so that disks hold the edges of one epoch, however many there are; of counts the contexts
go as well, as soon as the next epoch is written.

Counts in strict order follow equal edges once, with their number as a weight, where that leaves
half of the rows at most: such rows are then made once and written to the shared folder.
"""

from __future__ import annotations

import functools
import gc
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..balance import Slabs
from ..kernels import Search
from ..plan import bound
from ..sources.readers import scratch_path
from ..tree import PrefixTree
from .slabs import adjacency, alike, counted, listed, predicates, prepared

#: Candidate edges that a task looks at in one epoch; work left below which the next epoch is the last.
BUDGET, LEAST_WORK = 50_000_000, 5_000_000
#: A task that holds more than HEAVY edges for each candidate of its budget would load and copy more than it searches: there the budget is AN_EDGE candidates for each edge.
HEAVY, AN_EDGE = 4, 256
#: Epochs by the budget as it is; from then on it doubles, so that epochs stay few however much one slab has left.
EVEN = 3


def enough(budget: float, held: int) -> float:
    """The budget of a task that holds so many edges."""
    return budget if held <= HEAVY * budget else max(budget, AN_EDGE * held)


def let_go(spark: SparkSession) -> None:
    """Shuffle files go when the driver collects the frames that made them; by itself it does so long after the disks are full."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def remove(spark: SparkSession, path: str) -> None:
    """A folder of this run's own, on whatever file system the shared one is."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def often_equal(ready: DataFrame) -> bool:
    """Whether at most about half of the edges differ in ends, time and predicates; only the plan depends on it."""
    r = ready.agg(F.count("*").alias("n"), F.approx_count_distinct(F.xxhash64(*(c for c in ready.columns if c not in ("edge_id", "tie")))).alias("rows")).first()
    return 2 * r["rows"] <= r["n"]


class Epochs(NamedTuple):
    """found: (motif, n) or matches.  costs: a row an epoch (epoch, contexts, work, owners that the work asks for)."""

    found: DataFrame
    costs: list[tuple[int, int, int, int]]


def run(edges: DataFrame, tree: PrefixTree, delta: int, slabs: Slabs, mode: str = "count", ties: str = "strict", anchored: str | None = None, budget: int = BUDGET, least_work: int = LEAST_WORK, split_siblings: bool = True, offload: str = "all") -> Epochs:
    """``offload``: "all" deals every context by itself, "one" keeps those of a task together.  Without ``split_siblings`` contexts of one partial match stay together."""
    keep, wanted = mode != "count", predicates(tree)
    longest = max(map(len, tree.prefixes()))
    names = [f"v{k}" for k in range(max(bound(p) for p in tree.prefixes()))] + ([f"e{k}" for k in range(longest - 1)] if keep else [])
    numbers = ["held", "node", "t_first", "t_last", "tie_last", "skip", "take", "weight", *names]
    schema = "motif string, n bigint, edge_path string, slab bigint, origin bigint, " + ", ".join(f"{c} bigint" for c in numbers)
    fields = pa.schema([("motif", pa.string()), ("n", pa.int64()), ("edge_path", pa.string()), ("slab", pa.int64()), ("origin", pa.int64()), *((c, pa.int64()) for c in numbers)])

    def whole(part: dict, rows: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(part[f.name], f.type) if f.name in part else pa.nulls(rows, f.type) for f in fields], schema=fields)

    def searched(search: Search, begin: Iterator, slab: int, origin: int, most: float) -> Iterator[pa.RecordBatch]:
        total: dict[str, int] = {}
        for source in (begin, search.run(most)):
            for query, e, n in source:
                if keep:
                    block = listed(search.a, query, e)
                    yield whole({c: block.column(c) for c in ("motif", "edge_path", "t_first", "t_last")}, len(block))
                else:
                    total[query] = total.get(query, 0) + n
        if total:
            block = counted(total)
            yield whole({"motif": block.column(0), "n": block.column(1)}, len(block))
        held = len(search.a.t)
        for part in search.left(max(1, int(enough(budget, held)) // 4)):
            rows = len(part["take"])
            yield whole(part | {"slab": [slab] * rows, "origin": [origin] * rows, "held": [held] * rows}, rows)

    def first(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        a = adjacency(table, wanted, ties, weighed)
        owned = (table.column("owned").to_numpy() & table.column("may_start").to_numpy()).astype(bool)[a.order]
        search = Search(a, tree, delta, keep)
        slab, replica = key[0].as_py(), key[1].as_py()
        yield from searched(search, search.start(owned), slab, slab * 1_000 + replica, enough(budget, len(a.t)))

    def later(most: float):
        def work(key: tuple[pa.Scalar, ...], contexts: pa.Table, table: pa.Table) -> pa.Table:
            if not contexts.num_rows or not table.num_rows:
                return pa.Table.from_batches([], schema=fields)
            search = Search(adjacency(table, wanted, ties, weighed), tree, delta, keep)
            nodes = contexts.column("node").to_numpy()
            for node in sorted(set(nodes.tolist())):
                part = contexts.filter(pa.array(nodes == node))
                search.resume(node, {c: part.column(c).to_numpy(zero_copy_only=False) if isinstance(part.column(c), pa.Array) else part.column(c).to_numpy() for c in numbers if part.column(c).null_count == 0})
            slab, owner = key[0].as_py(), key[1].as_py()
            return pa.Table.from_batches(list(searched(search, iter(()), slab, slab * 1_000 + owner, enough(most, table.num_rows))), schema=fields)

        return work

    spark = edges.sparkSession
    folder, costs, paths = scratch_path(spark), [], []
    read = lambda path: spark.read.schema(schema).parquet(path)
    ready = prepared(edges, tree, anchored)
    weighed = not keep and ties == "strict" and often_equal(ready)
    if weighed:
        rows = alike(edges, tree, anchored)
        rows.write.parquet(f"{folder}/rows")
        let_go(spark)
        ready = spark.read.schema(rows.schema).parquet(f"{folder}/rows")
    out = slabs.assigned(ready).groupBy("slab", "replica").applyInArrow(first, schema)
    while True:
        paths.append(f"{folder}/{len(paths)}")
        out.write.parquet(paths[-1])
        let_go(spark)
        if not keep:  # a row a motif; what the epoch before left has been taken up
            read(paths[-1]).where("motif is not null").groupBy("motif").agg(F.sum("n").alias("n")).write.parquet(f"{paths[-1]}-counts")
            if len(paths) > 1:
                remove(spark, paths[-2])
        contexts = read(paths[-1]).where("node is not null").drop("motif", "n", "edge_path")
        grown = max(1, budget) << min(max(0, len(paths) - EVEN), 32)
        share = F.when(F.col("held") > HEAVY * grown, F.greatest(F.lit(grown), F.col("held") * AN_EDGE)).otherwise(F.lit(grown))
        asked = contexts.groupBy("slab").agg(F.sum("take").alias("work"), F.count("*").alias("contexts"), F.max("held").alias("held")).withColumn("of", F.ceil(F.col("work") / share).cast("int"))
        left = asked.agg(F.coalesce(F.sum("contexts"), F.lit(0)).alias("c"), F.coalesce(F.sum("work"), F.lit(0)).alias("w"), F.coalesce(F.sum("of"), F.lit(0)).alias("of")).first()
        costs.append((len(paths) - 1, left["c"], left["w"], left["of"]))
        if not left["c"]:
            break
        most = float("inf") if left["w"] <= least_work else grown
        apart = ["origin"] if offload == "one" else [c for c in numbers if split_siblings or c not in ("node", "skip", "take")]
        dealt = contexts.join(asked.select("slab", "of"), "slab").withColumn("owner", F.pmod(F.xxhash64(*apart), F.col("of")).cast("int")).drop("of")
        own = Slabs(slabs.delta, slabs.width, slabs.borders, 1, slabs.grid).assigned(ready).drop("replica").join(dealt.select("slab", "owner").distinct().toDF("slab", "owner"), "slab")
        out = dealt.groupBy("slab", "owner").cogroup(own.groupBy("slab", "owner")).applyInArrow(later(most), schema)
    if keep:
        found = functools.reduce(DataFrame.unionByName, [read(p).where("motif is not null") for p in paths])
        return Epochs(found.select("motif", "edge_path", "t_first", "t_last"), costs)
    for gone in (paths[-1], f"{folder}/rows"):
        remove(spark, gone)
    found = spark.read.schema("motif string, n bigint").parquet(*(f"{p}-counts" for p in paths))
    return Epochs(found.groupBy("motif").agg(F.sum("n").alias("n")), costs)
