"""As-of join, and the functions that Spark lets Python define: scalar, grouped and table-valued."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import kernels
from ..api import with_zeros
from ..balance import Slabs
from ..motif import Motif
from ..tree import PrefixTree


def as_of(left: DataFrame, right: DataFrame, key: str, t: str) -> DataFrame:
    """Each left row with the edge_id of the latest earlier right row of its key (null: none), by a window over the union."""
    both = left.withColumn("_left", F.lit(1)).unionByName(right.withColumn("_left", F.lit(0)))
    before = W.partitionBy(key).orderBy(t).rangeBetween(W.unboundedPreceding, -1)
    prior = F.last(F.when(F.col("_left") == 0, F.col("edge_id")), ignorenulls=True).over(before)
    return both.withColumn("prior_id", prior).where("_left = 1").drop("_left")


def edge_label(src: str, dst: str) -> Column:
    """``src>dst``, by an Arrow-batched function (the built-in concat does the same; this shows the path)."""

    @F.pandas_udf("string")
    def label(a: pd.Series, b: pd.Series) -> pd.Series:
        return a.astype(str) + ">" + b.astype(str)

    return label(src, dst)


def pingpongs(src: str, dst: str, t: str) -> Column:
    """Replies that go straight back, in a group's time order: a grouped aggregate in pandas."""

    @F.pandas_udf("long")
    def count(s: pd.Series, d: pd.Series, at: pd.Series) -> int:
        o = np.argsort(at.to_numpy(), kind="stable")
        a, b = s.to_numpy()[o], d.to_numpy()[o]
        return int(((a[:-1] != b[:-1]) & (b[:-1] == a[1:]) & (a[:-1] == b[1:])).sum())

    return count(src, dst, t)


def mining_udtf(motifs: list[Motif], delta: int):
    """A table function for SQL: rows of one slab in, (motif, n) out."""
    from pyspark.sql.functions import udtf

    tree = PrefixTree.build(motifs)

    class Mine:
        def __init__(self):
            self.rows = []

        def eval(self, row):
            self.rows.append((row["edge_id"], row["src"], row["dst"], row["t"], row["tie"], row["owned"]))

        def terminate(self):
            if self.rows:
                rows = sorted(self.rows, key=lambda r: (r[3], r[4]))
                a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
                yield from kernels.tally(kernels.specialised(tree), a, np.array([r[5] for r in rows], dtype=bool), delta).items()

    return udtf(Mine, returnType="motif string, n bigint")


def mined_by_sql(edges: DataFrame, motifs: list[Motif], delta: int, width: int) -> DataFrame:
    """Counts by a SQL statement that calls the table function on every slab."""
    spark = edges.sparkSession
    spark.udtf.register("mine_slab", mining_udtf(motifs, delta))
    dealt = Slabs(delta, width).assigned(edges).select("slab", "edge_id", "src", "dst", "t", "tie", "owned")
    dealt.createOrReplaceTempView("mine_slab_edges")
    tree = PrefixTree.build(motifs)
    out = spark.sql("SELECT motif, sum(n) AS n FROM mine_slab(TABLE(mine_slab_edges) PARTITION BY slab ORDER BY t) GROUP BY motif")
    return with_zeros(out, tree)


