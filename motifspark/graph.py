"""Temporal graphs as DataFrames of edges, and the stand-in graphs on the given tables."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

DAY = 86_400_000_000  # microseconds

EDGES = T.StructType([T.StructField(n, T.LongType()) for n in ("edge_id", "src", "dst", "t", "tie")])


def micros(c: str) -> Column:
    """Microseconds since 1970 of a time without zone; the session's zone plays no part."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {c})")


@dataclass
class TemporalGraph:
    """``edges`` has edge_id, src, dst, t (microseconds), tie and any attributes; ``sides`` tells that it is bipartite by construction."""

    edges: DataFrame
    vertices: DataFrame | None = None
    sides: bool | None = None
    name: str = ""
    _held: dict = field(default_factory=dict, repr=False)

    def labelled(self) -> DataFrame:
        """Edges with slabel and dlabel, where vertices have labels."""
        if self.vertices is None:
            return self.edges
        v = self.vertices.select("vid", "vlabel")
        return self.edges.join(v.toDF("src", "slabel"), "src", "left").join(v.toDF("dst", "dlabel"), "dst", "left")

    def static_edges(self) -> DataFrame:
        return self.edges.groupBy("src", "dst").agg(F.count("*").alias("n"))

    def vertex_ids(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()

    def profile(self) -> DataFrame:
        """One row: vertices, temporal_edges, static_edges, self_loops, span_us."""
        whole = self.edges.agg(F.count("*").alias("temporal_edges"), F.coalesce(F.sum((F.col("src") == F.col("dst")).cast("long")), F.lit(0)).alias("self_loops"), (F.max("t") - F.min("t")).alias("span_us"))
        return self.vertex_ids().agg(F.count("*").alias("vertices")).crossJoin(self.static_edges().agg(F.count("*").alias("static_edges"))).crossJoin(whole)

    def repeated_ids(self) -> DataFrame:
        """(edge_id, n) of ids that several edges share; where ids are hashes of rows, there must be none."""
        return self.edges.groupBy("edge_id").agg(F.count("*").alias("n")).where("n > 1")

    def store_layout(self, table: str, width: int, buckets: int) -> tuple[str, int]:
        """The adjacency that the fused engine joins with, stored in buckets of its join keys: it is never shuffled again."""
        from .engines.levels import DST, SRC, adjacency

        keys = ("g_end", "g_key", "g_bucket")
        adjacency(self.edges, width, {SRC, DST}).write.bucketBy(buckets, *keys).sortBy(*keys).mode("overwrite").saveAsTable(table)
        return table, int(width)

    def compact(self) -> tuple[TemporalGraph, DataFrame]:
        """Dense vertex numbers and times from the minimum; and the dictionary (vid, dense)."""
        from pyspark.sql import Window as W

        ids = self.vertex_ids().withColumn("cell", F.pmod(F.xxhash64("vid"), F.lit(1024)))
        sizes = ids.groupBy("cell").agg(F.count("*").alias("n"))
        starts = sizes.select("cell", (F.sum("n").over(W.orderBy("cell")) - F.col("n")).alias("start"))  # 1,024 rows
        words = ids.withColumn("r", F.row_number().over(W.partitionBy("cell").orderBy("vid"))).join(F.broadcast(starts), "cell").select("vid", (F.col("start") + F.col("r") - 1).alias("dense"))
        t0 = self.edges.agg(F.min("t").alias("t0"))
        e = self.edges.join(words.toDF("src", "s"), "src").join(words.toDF("dst", "d"), "dst").crossJoin(F.broadcast(t0))
        e = e.select("edge_id", F.col("s").alias("src"), F.col("d").alias("dst"), (F.col("t") - F.col("t0")).alias("t"), "tie")
        return TemporalGraph(e, None, self.sides, self.name), words

    def layouts(self, which: str, partitions: int | None = None) -> DataFrame:
        """Edges hashed by src, dst or both, sorted by time inside a partition: the adjacency of one step kind."""
        keys = {"src": ["src"], "dst": ["dst"], "pair": ["src", "dst"]}[which]
        dealt = self.edges.repartition(partitions, *keys) if partitions else self.edges.repartition(*keys)
        return dealt.sortWithinPartitions(*keys, "t", "tie")

    def subsample(self, fraction: float, mode: str = "span") -> TemporalGraph:
        """``span`` keeps a contiguous first part of the time (and every match inside it), ``edges`` thins by a hash."""
        if mode == "edges":
            kept = self.edges.where(F.pmod(F.xxhash64("edge_id"), F.lit(10_000)) < int(fraction * 10_000))
        else:
            span = self.edges.agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
            kept = self.edges.crossJoin(F.broadcast(span)).where(F.col("t") <= F.col("lo") + ((F.col("hi") - F.col("lo")) * fraction).cast("long")).select(self.edges.columns)
        return TemporalGraph(kept, self.vertices, self.sides, self.name)

    def cleaned(self, self_loops: bool = True) -> TemporalGraph:
        """Without null ends or times, negative times and rows that repeat; self-loops as wished."""
        e = self.edges.where("src is not null and dst is not null and t is not null and t >= 0").dropDuplicates(["src", "dst", "t", "tie"])
        return TemporalGraph(e if self_loops else e.where("src <> dst"), self.vertices, self.sides, self.name)

    def two_sided(self) -> DataFrame:
        """One row, bipartite: whether every edge joins a negative vertex and another, which is how the tables' graphs mark sides."""
        return self.edges.agg((F.count_if((F.col("src") < 0) == (F.col("dst") < 0)) == 0).alias("bipartite"))

    def is_bipartite(self, max_rounds: int = 64) -> bool:
        """Two-colouring by label propagation with pointer jumping.

        Each vertex holds a root and the parity of a way to it; it takes the smallest pair among
        its own, its neighbours' (parity turned) and its root's.  When nothing changes any more,
        the graph is bipartite iff no edge joins equal sides of one root.  Each round's labels
        are written to the shared folder and read again: no lineage grows, no executor's loss matters.
        """
        if self.sides is not None:
            return self.sides
        from .sources.readers import scratch_path

        spark = self.edges.sparkSession
        folder, kept = scratch_path(spark), 0

        def stored(df: DataFrame) -> DataFrame:
            nonlocal kept
            kept += 1
            df.write.parquet(f"{folder}/{kept}")
            return spark.read.schema(df.schema).parquet(f"{folder}/{kept}")

        pairs = self.edges.select("src", "dst").distinct()
        both = stored(pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
        if not both.where("src = dst").isEmpty():
            return False
        mark = F.struct("root", "side")
        label = stored(both.select(F.col("src").alias("v")).distinct().select("v", F.col("v").alias("root"), F.lit(0).alias("side")))
        for _ in range(max_rounds):
            near = both.join(label.select(F.col("v").alias("dst"), "root", (1 - F.col("side")).alias("side")), "dst").groupBy(F.col("src").alias("v")).agg(F.min(mark).alias("m"))
            step = label.join(near, "v").select("v", F.least(mark, F.col("m")).alias("b"), mark.alias("was"))
            jump = step.join(label.toDF("hop", "hop_root", "hop_side"), F.col("b.root") == F.col("hop"))
            jump = jump.select("v", F.least(F.col("b"), F.struct(F.col("hop_root").alias("root"), F.pmod(F.col("b.side") + F.col("hop_side"), F.lit(2)).alias("side"))).alias("b"), "was")
            new = stored(jump.select("v", F.col("b.root").alias("root"), F.col("b.side").alias("side"), (F.col("b") != F.col("was")).alias("moved")))
            label = new.select("v", "root", "side")
            if new.where("moved").isEmpty():
                break
        else:
            raise RuntimeError(f"the colouring has not settled after {max_rounds} rounds")
        clash = both.join(label.toDF("src", "r1", "s1"), "src").join(label.toDF("dst", "r2", "s2"), "dst").where("r1 = r2 and s1 = s2")
        return clash.isEmpty()


def from_edge_list(df: DataFrame, src: str = "src", dst: str = "dst", t: str = "t", edge_id: str | None = None, attrs: tuple[str, ...] = (), repeats: bool = True) -> TemporalGraph:
    """A graph from any table.

    Without an id column an edge's id is a hash of its row and, of rows that repeat whole, its number among them
    (one shuffle; ``repeats=False`` says that none do and spares it).
    """
    if edge_id:
        eid = F.col(edge_id)
    elif repeats:
        from pyspark.sql import Window as W

        df = df.select(src, dst, t, *attrs).withColumn("_copy", F.row_number().over(W.partitionBy(src, dst, t, *attrs).orderBy(F.lit(0))))
        eid = F.xxhash64(src, dst, t, *attrs, "_copy")
    else:
        eid = F.xxhash64(src, dst, t, *attrs)
    return TemporalGraph(df.select(eid.cast("long").alias("edge_id"), F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), F.col(t).cast("long").alias("t"), eid.cast("long").alias("tie"), *attrs))


def from_tables(spark: SparkSession, sf_dir: str, kind: str) -> TemporalGraph:
    """The stand-in graphs: msg, msg_hub, msg_day, trade, nation, chat."""
    read = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet")
    if kind in ("msg", "msg_hub", "msg_day"):
        e = read("events").select("event_id", "ts", "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("k"))
        n = read("events").agg((F.max("user_id") + 1).alias("n"))
        dst = F.expr("k % n") if kind == "msg_hub" else F.expr("(k + 100 * (event_id % 15)) % n")
        t = micros("date_trunc('DAY', ts)") if kind == "msg_day" else micros("ts")
        out = e.crossJoin(F.broadcast(n)).select(F.col("event_id").alias("edge_id"), F.col("user_id").cast("long").alias("src"), dst.cast("long").alias("dst"), t.alias("t"), F.col("event_id").alias("tie"), F.col("event_type").alias("etype"), F.col("value").alias("weight"))
        return TemporalGraph(out, None, False, kind)
    if kind in ("trade", "nation"):
        li = read("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_returnflag", "l_extendedprice")
        o = read("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
        j = li.join(o, "l_orderkey")
        eid = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
        if kind == "trade":
            back = F.col("l_returnflag") == "R"
            supplier = (-1 - F.col("l_suppkey")).cast("long")
            src, dst = F.when(back, supplier).otherwise(F.col("o_custkey")), F.when(back, F.col("o_custkey")).otherwise(supplier)
            return TemporalGraph(j.select(eid.alias("edge_id"), src.cast("long").alias("src"), dst.cast("long").alias("dst"), micros("l_shipdate").alias("t"), eid.alias("tie"), F.col("l_returnflag").alias("etype"), F.col("l_extendedprice").alias("weight")), None, True, kind)
        c, s = read("customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), read("supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
        j = j.join(c, "o_custkey").join(s, "l_suppkey")
        return TemporalGraph(j.select(eid.alias("edge_id"), F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst"), micros("l_shipdate").alias("t"), eid.alias("tie"), F.col("l_returnflag").alias("etype"), F.col("l_extendedprice").alias("weight")), None, False, kind)
    if kind == "chat":
        c = read("conversations").select("conv_id", "turn", "role")
        code = lambda r: F.when(F.col(r) == "user", 0).when(F.col(r) == "assistant", 1).otherwise(2).cast("long")
        after = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("role").alias("reply"))
        e = c.join(after, ["conv_id", "turn"])
        return TemporalGraph(e.select(F.expr("conv_id * 100000 + turn").alias("edge_id"), code("role").alias("src"), code("reply").alias("dst"), F.col("turn").alias("t"), F.expr("conv_id * 100000 + turn").alias("tie"), "conv_id"), None, False, kind)
    raise ValueError(f"no graph {kind!r}")
