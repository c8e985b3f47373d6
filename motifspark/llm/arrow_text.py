"""Arrow helpers for the operators that work on text in Python workers."""

from __future__ import annotations

import ctypes
import gc
import sys
import types
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Bytes of text that a worker looks at together; a longer text is a slice of its own.
SLICE_BYTES = 1 << 20

#: Rows in a batch between Spark and a Python worker; whole texts of thousands of rows would fill both.
BATCH_ROWS = 1_000


@contextmanager
def settings(spark: SparkSession, wanted: dict[str, str]):
    """Run-time settings for a block, put back afterwards."""
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def small_batches(spark: SparkSession):
    """For a block that writes what Python workers make: Arrow batches of BATCH_ROWS rows at most."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name))
    return settings(spark, {name: str(min(now, BATCH_ROWS) if now > 0 else BATCH_ROWS)})


def give_back() -> None:
    """Memory that a worker has freed goes back to the system: the worker lives on and serves other operators."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def map_arrow(df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """df.mapInArrow(work, schema), giving memory back at the end of each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from work(batches)
        finally:
            give_back()

    return df.mapInArrow(run, schema)


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts, one after the other, and len + 1 offsets; null texts are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None and len(column) else np.zeros(0, dtype=np.uint8)
    return buf, off - off[0] if len(off) else np.zeros(1, dtype=np.int64)


def slices(batch: pa.RecordBatch, text: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts have about ``most`` bytes together."""
    if not batch.num_rows:
        return
    _, off = utf8(batch.column(batch.schema.get_field_index(text)))
    at = 0
    while at < batch.num_rows:
        to = max(at + 1, int(np.searchsorted(off, off[at] + most, "right")) - 1)
        yield batch.slice(at, to - at)
        at = to


def per_process(name: str, make: Callable):
    """A value that a Python worker keeps from task to task (its functions are unpickled anew for each)."""
    held = sys.modules.setdefault("_motifspark_worker", types.ModuleType("_motifspark_worker")).__dict__
    if name not in held:
        held[name] = make()
    return held[name]
