"""Shared plumbing: scratch tables, size-checked broadcasts, components, ranks.

Scratch tables live below ``spark.checkpoint.dir`` so that every executor can
read them again after another one is lost.
"""

from __future__ import annotations

import atexit
import functools
import json
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow_text import give_back, map_arrow

#: Edges whose components one task finds by itself (16 bytes each).
TASK_EDGES = 50_000
#: Rows that may be broadcast: narrow rows (tens of bytes), so tens of MB at most.
BROADCAST_ROWS = 500_000
#: Bytes that wide rows may have together to be broadcast.
BROADCAST_BYTES = 64 << 20

#: ASCII white space, the separators that most contracts here name.
ASCII_SPACE = r"[\x20\x09-\x0D]+"


@functools.cache
def local_scratch() -> str:
    """This process's temporary folder, which goes with it."""
    folder = tempfile.mkdtemp(prefix="motifspark-")
    atexit.register(shutil.rmtree, folder, True)
    return folder


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder.  Where none is set, a temporary one in local mode (tests); elsewhere that is an error."""
    conf = spark.sparkContext.getConf()
    found = conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = "file://" + local_scratch()
    return found.rstrip("/")


def delete(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: Folders of the operators that run inside scratch_scope().
_SCOPES: list[list[str]] = []


@contextmanager
def scratch_scope(spark: SparkSession):
    """Deletes at its end what operators inside wrote to the shared folder: their results must be stored or used up by then."""
    _SCOPES.append([])
    try:
        yield
    finally:
        for root in _SCOPES.pop():
            delete(spark, root)


class Scratch:
    """Tables written to the shared folder and read again: a cut of lineage that survives lost executors."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        self.n = 0
        if _SCOPES:
            _SCOPES[-1].append(self.root)

    def path(self, name: str) -> str:
        self.n += 1
        return f"{self.root}/{self.n:03d}-{name}"

    def table(self, df: DataFrame, name: str, into: list | None = None) -> DataFrame:
        """Writes df and reads it again; ``into`` collects the path, for drop()."""
        path = self.path(name)
        df.write.parquet(path)
        if into is not None:
            into.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *paths: str) -> None:
        for path in paths:
            delete(self.spark, path)


def relieve(spark: SparkSession) -> None:
    """Memory that the driver has freed goes back to the system: its Python's, its JVM's heap, and what the C library keeps after plans were compiled."""
    give_back()
    jvm, array = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array
    jvm.System.gc()
    try:  # the bean's own class is not exported: called by the interface's method
        named = jvm.java.lang.Class.forName
        kinds, given = array(jvm.java.lang.Class, 4), array(jvm.java.lang.Object, 4)
        for k, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[k] = named(kind)
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        named("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Py4JError:  # a JVM that has no such command
        pass


def local_rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A small table that the driver made, as a relation of the JVM: no Python worker reads it."""
    names = [f.name for f in T._parse_datatype_string(schema).fields]
    jvm = spark.sparkContext._jvm
    held = jvm.java.util.ArrayList()
    held.add(json.dumps([dict(zip(names, r, strict=True)) for r in rows]))
    text = DataFrame(spark._jsparkSession.createDataset(held, jvm.org.apache.spark.sql.Encoders.STRING()).toDF(), spark)
    fields = ", ".join(f"{f.name}: {f.dataType.simpleString()}" for f in T._parse_datatype_string(schema).fields)
    return text.select(F.inline(F.from_json("value", f"array<struct<{fields}>>")))


def small(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS, width: Column | None = None) -> DataFrame:
    """df marked for broadcast if it has at most ``limit`` rows, else as it is (a shuffled join then).

    ``width``: bytes of a row that is not narrow; these together must stay under BROADCAST_BYTES too.
    """
    if width is not None:
        r = df.agg(F.count("*").alias("n"), F.coalesce(F.sum(width), F.lit(0)).alias("b")).first()
        return F.broadcast(df) if r["n"] <= limit and r["b"] <= BROADCAST_BYTES else df
    n = df.count() if rows is None else rows
    return F.broadcast(df) if n <= limit else df


def joined_hot(rows: DataFrame, unique: DataFrame, key: str, how: str = "inner", salts: int = 16) -> DataFrame:
    """rows joined with a table that has one row a key.

    A small table is broadcast.  Else rows of a key are dealt to ``salts`` tasks and the table's rows are
    copied as often, so that a key that holds a third of all rows is no single task.
    """
    n = unique.count()
    if n <= BROADCAST_ROWS:
        return rows.join(F.broadcast(unique), key, how)
    copies = unique.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    dealt = rows.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    return dealt.join(copies, [key, "_salt"], how).drop("_salt")


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df has not."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def row_key() -> Column:
    """A number for a row's doc_id and text: a doc_id may be null, or repeat with other texts."""
    return F.xxhash64("doc_id", "text")


def without(docs: DataFrame, rejected: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """The rows of docs that ``rejected`` does not name.

    It is given rows (doc_id, text) whose doc_id is the row's key, and returns rows with such a doc_id: a row is judged by
    its own id and text, whichever other row has the same id, or none.
    """
    name = fresh(docs, "_row")
    gone = rejected(docs.select(row_key().alias("doc_id"), "text")).select(F.col("doc_id").alias(name)).distinct()
    gone = Scratch(docs.sparkSession, "rejected").table(gone, "rows")
    return docs.withColumn(name, row_key()).join(small(gone), name, "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))


def keepers(docs: DataFrame, key: Column, verdicts: DataFrame) -> DataFrame:
    """The rows of docs that stay, one of those that repeat doc_id and text.

    ``key`` is a hash of a row's text; verdicts has rows (doc_id, key, gone, n), n how many rows share both.
    Only rows that repeat are shuffled to lose their copies.
    """
    name = fresh(docs, "_key")
    d = docs.withColumn(name, key).alias("d")
    v = verdicts.select(F.col("doc_id").alias("id"), F.col("key").alias("of"), "gone", "n")
    same = F.col("d.doc_id").eqNullSafe(F.col("v.id")) & (F.col(f"d.{name}") == F.col("v.of"))
    own = [F.col(f"d.`{c}`") for c in docs.columns]
    left = d.join(small(v.where("gone or n > 1").select("id", "of")).alias("v"), same, "left_anti").select(*own)
    again = v.where("not gone and n > 1").select("id", "of")
    if again.isEmpty():
        return left
    one = d.join(small(again).alias("v"), same, "left_semi").dropDuplicates(["doc_id", name])
    return left.unionByName(one.select(*(F.col(f"`{c}`") for c in docs.columns)))


def text_or_empty(c: str = "text") -> Column:
    return F.coalesce(F.col(c), F.lit(""))


def least_reachable(v: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices and the smallest vertex that each reaches: labels hang below smaller ones, paths are shortened to their ends."""
    ids, at = np.unique(np.concatenate((v, w)), return_inverse=True)
    x, y, c = at[: len(v)], at[len(v) :], np.arange(len(ids))
    while (c[x] != c[y]).any():
        least = np.minimum(c[x], c[y])
        new = c.copy()
        np.minimum.at(new, c[x], least)
        np.minimum.at(new, c[y], least)
        while ((c := new[new]) != new).any():
            new = c
    return ids, ids[c]


def united(edges: DataFrame) -> DataFrame:
    """(v, c) of at most TASK_EDGES edges (v, w), in one task."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if held := [b for b in batches if b.num_rows]:
            table = pa.Table.from_batches(held)
            v, c = least_reachable(table.column(0).to_numpy(), table.column(1).to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(v), pa.array(c)], ["v", "c"])

    return map_arrow(edges.select(F.col("v").cast("bigint"), F.col("w").cast("bigint")).repartition(1), work, "v bigint, c bigint")


def components(scratch: Scratch, edges: DataFrame, a: str, b: str) -> DataFrame:
    """Connected components of an edge list: rows (v, c), c the smallest vertex reachable.

    Up to TASK_EDGES edges are one task's work: rounds of joins would make the driver compile dozens
    of plans and hold a broadcast table for each join.  Beyond that, each round takes the smallest label among the neighbours and then the label of that
    label (pointer jumping), so that long chains take a logarithmic number of rounds.
    Grouping is by partial aggregates; no task collects a vertex's neighbours.
    An empty edge list gives no rows.
    """
    both = edges.select(F.col(a).alias("v"), F.col(b).alias("w")).where("v <> w")
    if edges.count() <= TASK_EDGES:
        return scratch.table(united(both), "labels")
    both = scratch.table(both.unionByName(both.select(F.col("w").alias("v"), F.col("v").alias("w"))).distinct(), "edges")
    label = scratch.table(both.groupBy("v").agg(F.least(F.min("w"), F.col("v")).alias("c")), "labels")
    while True:
        near = both.join(label.select(F.col("v").alias("w"), F.col("c").alias("cw")), "w").groupBy("v").agg(F.min("cw").alias("m"))
        step = label.join(near, "v").select("v", F.least("c", "m").alias("m"), F.col("c").alias("old"))
        jump = step.join(label.select(F.col("v").alias("m"), F.col("c").alias("cm")), "m", "left")
        new = scratch.table(jump.select("v", F.least("m", F.coalesce("cm", "m")).alias("c"), "old"), "labels")
        if new.where("c <> old").isEmpty():
            return new.select("v", "c")
        label = new.select("v", "c")


def ranked(df: DataFrame, group: list[str], order: list[Column], buckets: int, key: Column, out: str) -> DataFrame:
    """Adds a gapless rank from 0 inside each group without bringing a group into one task.

    Rows of a group are dealt to ``buckets`` buckets by ``key`` (rows alike in key share a bucket);
    ranks inside a bucket come from a window, their starts from the running sum of bucket sizes.
    The table of sizes has one row a group and bucket; it is joined, never collected.
    """
    from pyspark.sql import Window as W

    d = df.withColumn("_bucket", F.pmod(key, F.lit(buckets)).cast("int"))
    sizes = d.groupBy(*group, "_bucket").agg(F.count("*").alias("_n"))
    starts = sizes.select(*group, "_bucket", (F.sum("_n").over(W.partitionBy(*group).orderBy("_bucket")) - F.col("_n")).alias("_start"))
    inside = d.withColumn("_rank", F.row_number().over(W.partitionBy(*group, "_bucket").orderBy(*order)))
    return inside.join(starts, [*group, "_bucket"]).withColumn(out, (F.col("_start") + F.col("_rank") - 1).cast("long")).drop("_bucket", "_rank", "_start")
