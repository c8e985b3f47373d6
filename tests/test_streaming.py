"""Streams against batch."""

import os
import uuid

import pytest
from pyspark.sql import functions as F

from motifspark.api import MineSpec, mine
from motifspark.catalog import MOTIFS, group
from motifspark.graph import DAY, EDGES, from_tables
from motifspark.sources import readers
from motifspark.streaming import mining, windows

PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


@pytest.fixture
def rocks(spark):
    spark.conf.set(PROVIDER, ROCKS)
    yield spark
    spark.conf.unset(PROVIDER)


def finish(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()


def name():
    return "q" + uuid.uuid4().hex[:8]


def staged(spark, edges, path, files, extra=()):
    """Edges in files by time, one a micro-batch, then the sentinel's."""
    rows = sorted(edges.select("edge_id", "src", "dst", "t", "tie").collect(), key=lambda r: r.t)
    size = -(-len(rows) // files)
    for k in range(files):
        spark.createDataFrame(rows[k * size : (k + 1) * size], EDGES).coalesce(1).write.mode("append").parquet(path)
    for r in extra:
        spark.createDataFrame([r], EDGES).coalesce(1).write.mode("append").parquet(path)


def test_stateful_mining_equals_batch(rocks, sf_dir, tmp_path):
    g = from_tables(rocks, sf_dir, "msg")
    last = g.edges.agg(F.max("t")).collect()[0][0]
    path = str(tmp_path / "edges")
    staged(rocks, g.edges, path, 3, [(-1, None, None, last + 60 * DAY, -1), (-2, None, None, last + 61 * DAY, -2)])
    stream = rocks.readStream.schema(EDGES).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(path)
    n = name()
    finish(mining.mine_stream(stream, group("F2"), DAY, 4 * DAY), n)
    got = {r.motif: r.n for r in rocks.table(n).groupBy("motif").agg(F.sum("n").alias("n")).collect()}
    assert got == {r.motif: r.n for r in mine(MineSpec(g, group("F2"), DAY, engine="levels")).collect() if r.n}


def test_stream_join_equals_path2(spark, sf_dir, tmp_path):
    g = from_tables(spark, sf_dir, "msg")
    path = str(tmp_path / "edges")
    staged(spark, g.edges, path, 2)
    n = name()
    finish(mining.two_edge_join(spark.readStream.schema(EDGES).parquet(path), DAY), n)
    want = mine(MineSpec(g, [MOTIFS["path2"]], DAY, mode="enumerate", engine="levels"))
    assert sorted(f"{r.e0}-{r.e1}" for r in spark.table(n).collect()) == sorted(r.edge_path for r in want.collect())


def test_windows_on_a_stream(spark, sf_dir, tmp_path):
    events = readers.events(spark, sf_dir)
    path = str(tmp_path / "events")
    events.repartition(3).write.parquet(path)
    stream = windows.timed(spark.readStream.schema(readers.EVENTS).parquet(path))
    for make, key in ((windows.tumbling, "event_type"), (windows.sliding, "event_type")):
        n = name()
        finish(make(stream.withWatermark("at", "60 days")), n, "complete")
        assert sorted(map(tuple, windows.flat(spark.table(n), key).collect())) == sorted(map(tuple, windows.flat(make(windows.timed(events)), key).collect()))


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    """A row behind the watermark changes nothing and is counted; one within the lateness is taken."""
    path, day = str(tmp_path / "in"), 86_400_000_000
    kind = "at timestamp, event_type string"
    for k, times in enumerate([[1 * day, 2 * day], [20 * day], [21 * day], [1 * day + 5, 20 * day + 5], [40 * day]]):
        rows = spark.createDataFrame([(t,) for t in times], "t bigint").select(F.timestamp_micros("t").alias("at"), F.lit("x").alias("event_type"))
        rows.coalesce(1).write.mode("append").parquet(path)
        os.utime(next(f for f in sorted((tmp_path / "in").glob("*.parquet"), key=os.path.getmtime, reverse=True)), (1_000_000 + k, 1_000_000 + k))
    stream = spark.readStream.schema(kind).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("at", "3 days")
    n = name()
    q = windows.tumbling(stream).writeStream.outputMode("append").format("memory").queryName(n).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {r.w_start // day: r.n for r in windows.flat(spark.table(n)).collect()}
    assert got == {1: 1, 2: 1, 20: 2, 21: 1}
    assert windows.counted_late(q) == 1


def test_a_restarted_stream_goes_on(spark, tmp_path):
    """Update mode: a query stopped after some files and started again from its checkpoint counts each row once."""
    path, out, day = str(tmp_path / "in"), str(tmp_path / "out"), 86_400_000_000
    for part in range(3):
        spark.range(10).select(F.timestamp_micros(F.col("id") * day + part).alias("at"), F.lit("x").alias("event_type")).coalesce(1).write.mode("append").parquet(path)
        stream = spark.readStream.schema("at timestamp, event_type string").parquet(path).withWatermark("at", "60 days")
        q = windows.tumbling(stream).writeStream.outputMode("update").foreachBatch(mining.append_once(out)).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
        q.awaitTermination()
    latest = spark.read.parquet(out).groupBy("w").agg(F.max_by("n", "batch").alias("n"))
    assert sorted(r.n for r in latest.collect()) == [3] * 10
    assert spark.read.parquet(out).select("batch").distinct().count() == 3


def test_parallel_edges_stream_in_whole(rocks, tmp_path):
    """Edges that repeat whole, with ids of their own, are all counted."""
    from motifspark.graph import TemporalGraph, from_edge_list

    rows = rocks.createDataFrame([(1, 2, 10 * DAY), (1, 2, 10 * DAY), (2, 3, 10 * DAY + 5), (2, 3, 10 * DAY + 5)], "src bigint, dst bigint, t bigint")
    g = TemporalGraph(from_edge_list(rows).edges)
    path = str(tmp_path / "edges")
    staged(rocks, g.edges, path, 1, [(-1, None, None, 90 * DAY, -1), (-2, None, None, 91 * DAY, -2)])
    n = name()
    finish(mining.mine_stream(rocks.readStream.schema(EDGES).option("maxFilesPerTrigger", 1).parquet(path), [MOTIFS["path2"]], DAY, 4 * DAY), n)
    assert {r.motif: r.n for r in rocks.table(n).groupBy("motif").agg(F.sum("n").alias("n")).collect()} == {"path2": 4}


def test_batches_are_written_once(spark, tmp_path):
    write, out = mining.append_once(str(tmp_path / "out")), str(tmp_path / "out")
    for _ in range(2):  # the second time is a replay
        write(spark.range(5), 0)
    write(spark.range(3), 1)
    assert spark.read.parquet(out).count() == 8


@pytest.mark.parametrize("format_", ["text", "json", "csv", "orc", "parquet"])
def test_edge_lists(spark, tmp_path, format_):
    e = spark.createDataFrame([(0, 1, 2, 3, 0), (1, -4, 5, 6, 1)], EDGES)
    readers.write_edge_list(e, str(tmp_path / format_), format_)
    assert sorted(map(tuple, readers.edge_list(spark, str(tmp_path / format_), format_).collect())) == [(-4, 5, 6), (1, 2, 3)]


def test_python_source_and_sinks(spark, tmp_path):
    spark.dataSource.register(readers.RingSource)
    e = spark.read.format("motif_edges").option("edges", 50).load()
    from motifspark.graph import TemporalGraph

    assert {r.motif: r.n for r in mine(MineSpec(TemporalGraph(e), [MOTIFS["tri_cycle"]], 2, engine="levels")).collect()} == {"tri_cycle": 48}
    readers.write_slabs(e, str(tmp_path / "slabs"), 10)
    assert spark.read.parquet(str(tmp_path / "slabs")).where("slab = 2").count() == 10
