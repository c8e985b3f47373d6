"""Exact dedup by a streaming query whose keyed state never expires.

Every row's digest flows through a streaming aggregation.  Its state, on disk in
RocksDB, retains for each digest the smallest stable identifier seen, the locator of that
row's content (which file, which row of it) and the number of rows.  There is no
watermark, so nothing ever leaves the state.  A caller that names a ``state`` folder owns
it: each call continues where the last one ended, and a copy that arrives a year later is
still found.  Without one the state lives for one call.

A row whose digest the state has twice is a hit, and only hits are read again, by their
locators: whole normalised bytes under one digest (of this call's rows, and of the row
retained from an earlier call) must agree.  They are grouped by digest and bytes with
map-side combining, so that a hot text is one row a task.  Texts that differ under one
digest are dealt with text by text.

Defined results.  Null text counts as empty; all empty texts are one group.  Rows that
repeat a doc_id and its text get the same verdict.  An empty table gives no rows.  Extra
columns are ignored by ``classes`` and returned by ``survivors``, whatever their names.  A
null doc_id is kept only if its whole group has none.  A table that no file holds (its rows
have no locator) is written below the state first.
"""

from __future__ import annotations

import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow_text import settings
from .common import ASCII_SPACE, Scratch, keepers, small, text_or_empty

#: Settings of the state store while its query runs; memory is bounded for all stores of an executor together.
STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "100",
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
}


def normalised(text: str = "text"):
    return F.regexp_replace(text_or_empty(text), ASCII_SPACE, " ")


def located(docs: DataFrame, scratch: Scratch, doc_id: str, text: str) -> DataFrame:
    """Rows (id, text, file, row): where each row's content can be read again; docs that no file holds are written first."""
    rows = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("text"))
    place = [F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row")]
    try:
        return docs.select(F.col(doc_id).alias("id"), F.col(text).alias("text"), *place)
    except AnalysisException:
        return scratch.table(rows, "content").select("id", "text", *place)


def digested(rows: DataFrame) -> DataFrame:
    """Rows (id, digest, file, row), the file by a hash of its name, from rows of ``located``."""
    return rows.select("id", F.unhex(F.sha2(normalised(), 256)).alias("digest"), F.xxhash64("file").alias("file"), "row")


def run_state(spark: SparkSession, root: str, schema, files_per_trigger: int | None = None) -> DataFrame:
    """Streams what is new in the folder ``root``/arrivals through the keyed state; rows (digest, first, n) of all calls so far.

    Each micro-batch's changes are appended to an update log.  Both columns move one way
    only, so a replayed batch changes nothing: the log's minimum and maximum are the state.
    """
    log = f"{root}/updates"
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", "true")
    if files_per_trigger:
        stream = stream.option("maxFilesPerTrigger", files_per_trigger)
    first = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "file", "row")).alias("first")
    state = stream.parquet(f"{root}/arrivals").groupBy("digest").agg(first, F.count("*").alias("n"))

    def append(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{log}/batch-{number}")

    with settings(spark, STATE):
        q = state.writeStream.outputMode("update").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(append).start()
        q.awaitTermination()
    kind = schema["id"].dataType.simpleString()
    fields = f"digest binary, first struct<none: boolean, id: {kind}, file: bigint, row: bigint>, n bigint"
    try:
        rows = spark.read.schema(fields).option("recursiveFileLookup", "true").parquet(log)
    except AnalysisException:  # nothing has ever arrived
        return spark.createDataFrame([], fields)
    return rows.groupBy("digest").agg(F.min("first").alias("first"), F.max("n").alias("n"))


def read_content(files: DataFrame, wanted: DataFrame, text: str) -> DataFrame:
    """(digest, norm) for locators (digest, file, row), read from the files that hold them; files: rows (file, path, text)."""
    spark = files.sparkSession
    held = [tuple(r) for r in wanted.select("file").distinct().join(files, "file").select("path", "text").distinct().collect()]  # names of files, as few as hold retained rows that are hit
    out = None
    for column in sorted({t for _, t in held}):
        rows = spark.read.parquet(*[p for p, t in held if t == column])
        rows = rows.select(F.xxhash64("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"), normalised(column).alias("norm"))
        out = rows if out is None else out.unionByName(rows)
    if out is None:
        return spark.createDataFrame([], "digest binary, norm string")
    return out.join(small(wanted), ["file", "row"]).select("digest", "norm")


def classes(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", files_per_trigger: int | None = None, state: str | None = None) -> DataFrame:
    """One row a row of docs: doc_id, keep_id, group_size, kept, text_sha256.

    ``state``: a folder that the caller keeps; rows are then judged with those of all earlier calls, whose
    files must still be where they were.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "exact-dedup")
    own = state or scratch.path("keyed")
    call = uuid.uuid4().hex
    if state:
        scratch.root = f"{state}/content-{call}"
    rows = located(docs, scratch, doc_id, text)
    new = digested(rows)
    new.write.parquet(f"{own}/arrivals/{call}")
    arrivals = spark.read.schema(new.schema).parquet(f"{own}/arrivals/{call}")
    named = rows.select("file").distinct().select(F.xxhash64("file").alias("file"), F.col("file").alias("path"))
    at: list[str] = []
    if state:
        content = "text" if "content-" in (rows.select("file").first() or [""])[0] else text
        named.withColumn("text", F.lit(content)).write.mode("append").parquet(f"{own}/files")
    now = run_state(spark, own, new.schema, files_per_trigger)
    if state:
        now = now.join(arrivals.select("digest").distinct(), "digest", "left_semi")
    now = scratch.table(now.select("digest", F.col("first.id").alias("keep_id"), F.col("first.file").alias("file"), F.col("first.row").alias("row"), "n"), "digests", at)

    # Hits only: the whole bytes of what shares a digest must agree.
    hits = arrivals.join(now.where("n > 1").select("digest"), "digest", "left_semi").select("digest", F.col("file").alias("of"), F.col("row").alias("at"))
    hits = scratch.table(hits, "hits", at)
    own_text = rows.select("id", "text", F.xxhash64("file").alias("file"), "row").alias("r").join(small(hits).alias("h"), (F.col("r.file") == F.col("h.of")) & (F.col("r.row") == F.col("h.at")))
    texts = own_text.select("id", "digest", normalised("r.text").alias("norm")).groupBy("digest", "norm").agg(F.min("id").alias("least"), F.count("*").alias("m"))
    several = texts.select("digest", "norm")
    if state:
        before = now.where("n > 1").join(arrivals.select("file", "row"), ["file", "row"], "left_anti").select("digest", "file", "row")
        kept = read_content(spark.read.parquet(f"{own}/files"), scratch.table(before, "retained"), text)
        several = several.unionByName(kept).distinct()
    differ = scratch.table(several.groupBy("digest").agg(F.count("*").alias("k")).where("k > 1").select("digest"), "collisions", at)

    out = arrivals.select("id", "digest").join(now.select("digest", "keep_id", "n"), "digest")
    if not differ.isEmpty():
        wrong = own_text.select("id", "digest", normalised("r.text").alias("norm")).join(F.broadcast(differ), "digest", "left_semi")
        right = wrong.join(texts.join(F.broadcast(differ), "digest", "left_semi"), ["digest", "norm"])
        out = out.join(F.broadcast(differ), "digest", "left_anti").unionByName(right.select("id", "digest", F.col("least").alias("keep_id"), F.col("m").alias("n")))
    return out.select(
        F.col("id").alias("doc_id"),
        "keep_id",
        F.col("n").cast("long").alias("group_size"),
        F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def survivors(docs: DataFrame) -> DataFrame:
    """The rows of docs that stay, one of each group, with all their columns."""
    groups = classes(docs).where("group_size > 1").groupBy("doc_id", F.unhex("text_sha256").alias("key")).agg(F.first(~F.col("kept")).alias("gone"), F.count("*").alias("n"))
    verdicts = Scratch(docs.sparkSession, "exact-dedup").table(groups, "verdicts")
    return keepers(docs, F.unhex(F.sha2(normalised(), 256)), verdicts)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents
)
SELECT doc_id,
       min(doc_id) OVER (PARTITION BY norm) AS keep_id,
       count(*) OVER (PARTITION BY norm) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY norm) AS kept,
       sha256(norm) AS text_sha256
FROM d
"""
