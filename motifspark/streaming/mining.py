"""Stateful co-mining of a stream of edges.

Edges go to slabs of fixed width (with their halo); a slab's state is the list of its
edges.  When the watermark passes the slab's end and the window after it, an event-time
timer fires: the slab is mined by the same kernel as in batch, the result goes out and the
state is cleared.  So the state holds one slab and its halo a key, never a whole history.

The last slabs stay open until the watermark passes them: a run that ends sends a
sentinel edge (negative edge_id) later than everything, which opens no match.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from .. import kernels
from ..balance import Slabs
from ..motif import Motif
from ..tree import PrefixTree

STATE = "edge_id long, src long, dst long, t long, tie long, owned boolean"
RESULT = "slab long, motif string, n long"


class SlabMiner(StatefulProcessor):
    def __init__(self, motifs: list[Motif], delta: int, width: int):
        self.tree, self.delta, self.width = PrefixTree.build(motifs), delta, width

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.edges = handle.getListState("edges", STATE)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        new = []
        for pdf in rows:
            real = pdf[pdf["real"]]
            new += [tuple(r) for r in zip(*(real[c].tolist() for c in ("edge_id", "src", "dst", "t", "tie", "owned")), strict=True)]
        if new:
            self.edges.appendList(new)
            # The slab is complete when no edge within the window after it can come any more.
            self.handle.registerTimer(((key[0] + 1) * self.width + self.delta) // 1000 + 1)
        yield pd.DataFrame({"slab": pd.Series([], dtype="int64"), "motif": pd.Series([], dtype=object), "n": pd.Series([], dtype="int64")})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        rows = sorted(self.edges.get(), key=lambda r: (r[3], r[4]))
        counts: dict[str, int] = {}
        if rows:
            a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
            counts = kernels.tally(kernels.specialised(self.tree), a, np.array([r[5] for r in rows], dtype=bool), self.delta)
        self.edges.clear()
        yield pd.DataFrame({"slab": pd.Series([key[0]] * len(counts), dtype="int64"), "motif": pd.Series(list(counts), dtype=object), "n": pd.Series(list(counts.values()), dtype="int64")})

    def close(self) -> None:
        pass


def mine_stream(edges: DataFrame, motifs: list[Motif], delta: int, slab_width: int, lateness: str = "1 hour") -> DataFrame:
    """(slab, motif, n) of finished slabs, append mode.  edges: a stream (edge_id, src, dst, t, tie); later than ``lateness``: dropped.

    A row without ends is no edge; it only says that time has come so far.

    Needs the RocksDB state store provider; one row of state is one edge.
    """
    timed = edges.withColumn("at", F.timestamp_micros("t")).withWatermark("at", lateness)
    dealt = Slabs(delta, slab_width).assigned(timed)
    dealt = dealt.select("slab", "edge_id", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("src", "dst")), "t", "tie", "owned", (F.col("src").isNotNull() & F.col("dst").isNotNull()).alias("real"), "at")
    return dealt.groupBy("slab").transformWithStateInPandas(SlabMiner(motifs, delta, slab_width), outputStructType=RESULT, outputMode="append", timeMode="EventTime")


def two_edge_join(edges: DataFrame, delta: int, lateness: str = "1 hour") -> DataFrame:
    """``path2`` as a stream-stream join with watermarks on both sides and a time range: (e0, e1)."""
    a = edges.select(F.col("edge_id").alias("e0"), F.col("src").alias("v0"), F.col("dst").alias("v1"), F.timestamp_micros("t").alias("at0")).where("v0 <> v1").withWatermark("at0", lateness)
    b = edges.select(F.col("edge_id").alias("e1"), F.col("src").alias("w1"), F.col("dst").alias("v2"), F.timestamp_micros("t").alias("at1")).withWatermark("at1", lateness)
    span = F.expr(f"at1 > at0 AND at1 <= at0 + INTERVAL {int(delta) / 1_000_000:.6f} SECONDS")
    return a.join(b, (F.col("w1") == F.col("v1")) & (F.col("v2") != F.col("v0")) & (F.col("v2") != F.col("v1")) & span).select("e0", "e1")


def append_once(path: str):
    """A foreachBatch function: each batch replaces its own folder, so a replayed batch changes nothing."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return write
