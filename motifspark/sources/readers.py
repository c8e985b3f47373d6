"""Readers with explicit schemas, the text edge list, a Python data source and the sinks."""

from __future__ import annotations

import atexit
import functools
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
EDGE_LIST = "src bigint, dst bigint, t bigint"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events, with no look at the files for a schema; filters and columns reach the scan."""
    return spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")


def edge_list(spark: SparkSession, path: str, format_: str = "text") -> DataFrame:
    """Edges ``u v t``: as text with blanks, json, csv, orc or parquet."""
    if format_ == "text":
        return spark.read.schema(EDGE_LIST).csv(path, sep=" ")
    return spark.read.schema(EDGE_LIST).format(format_).load(path)


def write_edge_list(edges: DataFrame, path: str, format_: str = "text") -> None:
    rows = edges.select("src", "dst", "t")
    if format_ == "text":
        rows.write.csv(path, sep=" ")
    else:
        rows.write.format(format_).save(path)


@functools.cache
def local_scratch() -> str:
    """This process's temporary folder, which goes with it."""
    folder = tempfile.mkdtemp(prefix="motifspark-")
    atexit.register(shutil.rmtree, folder, True)
    return folder


def scratch_path(spark: SparkSession) -> str:
    """A new folder in the cluster's shared one.  Where none is set, a temporary one in local mode (tests); elsewhere that is an error."""
    shared = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not shared:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        shared = f"file://{local_scratch()}"
    return f"{shared.rstrip('/')}/edges-{uuid.uuid4().hex[:12]}"


def roundtrip(edges: DataFrame, format_: str = "text") -> DataFrame:
    path = scratch_path(edges.sparkSession)
    write_edge_list(edges, path, format_)
    return edge_list(edges.sparkSession, path, format_)


def write_slabs(edges: DataFrame, path: str, width: int) -> None:
    """Parquet by time slab, sorted inside: a new day's mining reads the slabs it touches."""
    edges.withColumn("slab", F.expr(f"t div {int(width)}")).repartition("slab").sortWithinPartitions("slab", "src", "t").write.partitionBy("slab").parquet(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int, key: str = "src") -> None:
    """A table bucketed and sorted on a step's key: joins on the key need no shuffle of the edges."""
    edges.write.bucketBy(buckets, key).sortBy(key, "t").mode("overwrite").saveAsTable(table)


class Ranges(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class RingSource(DataSource):
    """``motif_edges``: a ring of n vertices that passes a token once a microsecond; known counts, for tests and soak runs."""

    @classmethod
    def name(cls) -> str:
        return "motif_edges"

    def schema(self) -> str:
        return "edge_id bigint, src bigint, dst bigint, t bigint, tie bigint"

    def reader(self, schema) -> DataSourceReader:
        return RingReader(int(self.options.get("edges", 100)), int(self.options.get("vertices", 3)))


class RingReader(DataSourceReader):
    def __init__(self, edges: int, vertices: int):
        self.edges, self.vertices = edges, vertices

    def partitions(self):
        step = max(1, self.edges // 4)
        return [Ranges(lo, min(self.edges, lo + step)) for lo in range(0, self.edges, step)]

    def read(self, partition):
        for k in range(partition.lo, partition.hi):
            yield k, k % self.vertices, (k + 1) % self.vertices, k, k
