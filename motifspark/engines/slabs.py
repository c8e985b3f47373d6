"""The slab engine: time is cut into slabs, each is finished depth first in one task.

A task gets the slab's own edges and those of the following window (the halo).  A match is
counted where its first edge is owned, and its first edge has one owner only: one slab, one
replica.  The only shuffle brings edges to slabs.  Matches leave a task block by block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import kernels
from ..balance import Slabs
from ..tree import PrefixTree

COUNTS = "motif string, n bigint"
MATCHES = "motif string, edge_path string, t_first bigint, t_last bigint"


def predicates(tree: PrefixTree) -> list[str]:
    return sorted({w for p in tree.prefixes() for _, _, w in p if w})


def prepared(edges: DataFrame, tree: PrefixTree, anchored: str | None = None) -> DataFrame:
    """The columns that kernels read; every predicate of the tree becomes a Boolean column."""
    flags = [F.coalesce(F.expr(w), F.lit(False)).alias(f"p{k}") for k, w in enumerate(predicates(tree))]
    return edges.select("edge_id", "src", "dst", "t", "tie", *flags, (F.coalesce(F.expr(anchored), F.lit(False)) if anchored else F.lit(True)).alias("may_start"))


def adjacency(rows: pa.Table, tree_predicates: list[str], ties: str, weighed: bool = False) -> kernels.Adjacency:
    column = lambda c: rows.column(c).to_numpy(zero_copy_only=False) if isinstance(rows.column(c), pa.Array) else rows.column(c).to_numpy()
    passes = {w: column(f"p{k}").astype(bool) for k, w in enumerate(tree_predicates)}
    return kernels.Adjacency(*(column(c).astype(np.int64) for c in ("edge_id", "src", "dst", "t", "tie")), ties, passes, column("n").astype(np.int64) if weighed else None)


def counted(total: dict[str, int]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), pa.array(list(total.values()), pa.int64())], ["motif", "n"])


def listed(a: kernels.Adjacency, query: str, e: list[np.ndarray]) -> pa.RecordBatch:
    """One block of matches."""
    ids = np.stack([a.edge_id[x] for x in e], axis=1)
    paths = ["-".join(map(str, r)) for r in ids.tolist()]
    return pa.RecordBatch.from_arrays([pa.array([query] * len(paths)), pa.array(paths, pa.string()), pa.array(a.t[e[0]]), pa.array(a.t[e[-1]])], ["motif", "edge_path", "t_first", "t_last"])


def rows(kernel, a: kernels.Adjacency, owned: np.ndarray, delta: int, mode: str) -> Iterator[pa.RecordBatch]:
    if mode == "count":
        yield counted(kernels.tally(kernel, a, owned, delta))
    else:
        for query, e in kernels.found(kernel, a, owned, delta):
            yield listed(a, query, e)


def run(edges: DataFrame, tree: PrefixTree, delta: int, slabs: Slabs, mode: str = "count", ties: str = "strict", kernel: str = "special", split_siblings: int = 0, anchored: str | None = None) -> DataFrame:
    """(motif, n) partial counts summed, or match rows.

    ``split_siblings``: so many levels of branchings, from the root on, whose children are tasks of their own; the
    shared prefix is recomputed there.
    """
    wanted = predicates(tree)
    make = {"special": kernels.specialised, "generic": kernels.generic}[kernel]
    branches = tree.split(int(split_siblings))

    def work(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        a = adjacency(table, wanted, ties)
        owned = (table.column("owned").to_numpy() & table.column("may_start").to_numpy()).astype(bool)[a.order]
        del table
        yield from rows(make(branches[key[2].as_py()]), a, owned, delta, mode)

    dealt = slabs.assigned(prepared(edges, tree, anchored)).withColumn("branch", F.explode(F.sequence(F.lit(0), F.lit(len(branches) - 1))))
    out = dealt.groupBy("slab", "replica", "branch").applyInArrow(work, COUNTS if mode == "count" else MATCHES)
    return out.groupBy("motif").agg(F.sum("n").alias("n")) if mode == "count" else out


def alike(edges: DataFrame, tree: PrefixTree, anchored: str | None = None) -> DataFrame:
    """The edges that kernels read, one row for all that agree in ends, time and predicates, with their number ``n``."""
    ready = prepared(edges, tree, anchored)
    kept = [c for c in ready.columns if c not in ("edge_id", "tie")]
    return ready.groupBy(*kept).agg(F.count("*").alias("n"), F.min("edge_id").alias("edge_id")).withColumn("tie", F.lit(0).cast("long"))


def run_alike(rows: DataFrame, tree: PrefixTree, delta: int, slabs: Slabs) -> DataFrame:
    """(motif, n) in strict order from what ``alike`` gives: equal edges are followed once."""
    wanted = predicates(tree)

    def work(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        a = adjacency(table, wanted, "strict", True)
        owned = (table.column("owned").to_numpy() & table.column("may_start").to_numpy()).astype(bool)[a.order]
        del table
        yield counted(kernels.weighted(tree, a, owned, delta))

    return slabs.assigned(rows).groupBy("slab", "replica").applyInArrow(work, COUNTS).groupBy("motif").agg(F.sum("n").alias("n"))


def run_scoped(edges: DataFrame, tree: PrefixTree, delta: int, scope: str, ties: str = "strict") -> DataFrame:
    """(scope, motif, n): matches whose edges all have the same value in the scope column."""
    wanted, make = predicates(tree), kernels.specialised

    def work(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        total = kernels.tally(make(tree), adjacency(table, wanted, ties), np.ones(table.num_rows, dtype=bool), delta)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()] * len(total), key[0].type), *counted(total).columns], [scope, "motif", "n"])

    kind = edges.schema[scope].dataType.simpleString()
    flags = [F.coalesce(F.expr(w), F.lit(False)).alias(f"p{k}") for k, w in enumerate(wanted)]
    return edges.select(scope, "edge_id", "src", "dst", "t", "tie", *flags).groupBy(scope).applyInArrow(work, f"{scope} {kind}, motif string, n bigint")
