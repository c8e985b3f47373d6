"""Uniform shuffle into shards of exact sizes by a hypergeometric communication matrix.

Rows lie in P logical partitions (a hash of the row, so that a retried task sees the
same ones).  Given the partition sizes, the driver draws how many rows of each partition
go to each shard: one multivariate hypergeometric draw a partition from what the shards
still lack, which is exactly the law of those counts under a uniform permutation.  Then
each partition permutes its rows at random, hands consecutive runs to the shards as the
matrix says, and each shard permutes what it received.  The law is ``rows``: sizes of
shards differ by one row at most.

The matrix has P rows and one column a shard; P is bounded (MAX_PARTITIONS), so the
matrix is small whatever the input is.  All random keys are hashes of seed and row:
a task that runs twice makes the same choice.

Defined results.  Null text has size 8 and the checksum of the empty text.  Repeated rows
are placed one by one.  An empty table gives no rows.  Extra columns pass through
``shard`` whatever their names (inside, a row travels as one struct); columns named like its
results (shard, slot) are replaced.  Null keys are keys like others.  The key should tell
rows apart: rows alike in it share a partition and a cell.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import local_rows, text_or_empty

MAX_PARTITIONS = 8192
ROWS_A_PARTITION = 20_000


def communication_matrix(sizes: np.ndarray, shards: int, seed: int) -> np.ndarray:
    """Rows: partitions, columns: shards.  Row sums are the sizes, column sums differ by one at most."""
    total = int(sizes.sum())
    lacks = np.array([total // shards + (s < total % shards) for s in range(shards)], dtype=np.int64)
    rng = np.random.Generator(np.random.PCG64(seed))
    out = np.zeros((len(sizes), shards), dtype=np.int64)
    for p, n in enumerate(sizes):
        left, drawn, pool = int(n), out[p], int(lacks.sum())
        for s in range(shards):
            if not left:
                break
            pool -= int(lacks[s])
            drawn[s] = hypergeometric(rng, int(lacks[s]), pool, left)
            left -= int(drawn[s])
        lacks -= drawn
    return out


def hypergeometric(rng: np.random.Generator, good: int, bad: int, sample: int) -> int:
    """An exact draw (to the rounding of doubles): numpy's below its limit of 10**9, by inversion around the mode from there on."""
    if good == 0 or sample == 0:
        return 0
    if bad == 0:
        return min(sample, good)
    if good + bad < 1_000_000_000:
        return int(rng.hypergeometric(good, bad, sample))
    n = good + bad
    low, high = max(0, sample - bad), min(good, sample)
    mode = min(max((sample + 1) * (good + 1) // (n + 2), low), high)
    # Beyond this many rows from the mode all chances together are less than a double resolves.
    reach = 60 + int(12 * (sample * (good / n) * (bad / n) * ((n - sample) / (n - 1))) ** 0.5)
    low, high = max(low, mode - reach), min(high, mode + reach)
    # Chances relative to the mode's, from the ratios of neighbours.
    k = np.arange(mode, high, dtype=np.float64)
    above = np.cumprod((good - k) / (k + 1) * ((sample - k) / (bad - sample + k + 1)))
    k = np.arange(mode, low, -1, dtype=np.float64)
    below = np.cumprod(k / (good - k + 1) * ((bad - sample + k) / (sample - k + 1)))
    chances = np.cumsum(np.concatenate((below[::-1], [1.0], above)))
    return low + min(int(np.searchsorted(chances, rng.random() * chances[-1], side="right")), high - low)


def shard(df: DataFrame, shards: int, key: list, seed: int = 0, partitions: int | None = None) -> DataFrame:
    """df with ``shard`` (int) and ``slot`` (long, gapless from 0 inside the shard)."""
    spark = df.sparkSession
    # The row is one struct, and what is needed of its key another: no name of the caller's meets one of ours.
    kept = [c for c in df.columns if c not in ("shard", "slot")]
    rows = df.select(F.struct(*(F.col(f"`{c}`") for c in kept)).alias("row"), F.struct(*(k.alias(f"k{i}") for i, k in enumerate(key))).alias("key"))
    if partitions is None:
        partitions = int(min(MAX_PARTITIONS, max(8, df.count() // ROWS_A_PARTITION)))
    draw = lambda what: F.xxhash64(F.lit(seed), F.lit(what), "key")
    rows = rows.withColumn("p", F.pmod(draw("partition"), F.lit(partitions)).cast("int"))
    sizes = np.zeros(partitions, dtype=np.int64)
    for r in rows.groupBy("p").agg(F.count("*").alias("n")).collect():  # at most MAX_PARTITIONS rows
        sizes[r["p"]] = r["n"]
    ends = communication_matrix(sizes, shards, seed).cumsum(axis=1)
    matrix = local_rows(spark, [(p, ends[p].tolist()) for p in range(partitions)], "p int, ends array<bigint>")
    sent = rows.withColumn("rank", F.row_number().over(W.partitionBy("p").orderBy(draw("local"), "key")))
    sent = sent.join(F.broadcast(matrix), "p").withColumn("shard", F.size(F.filter("ends", lambda e: e < F.col("rank"))).cast("int")).drop("ends", "rank", "p")
    # The shard's own permutation, by cells: a random cell, then a random order inside it.
    sent = sent.withColumn("cell", F.pmod(draw("cell"), F.lit(partitions)).cast("int"))
    cells = sent.groupBy("shard", "cell").agg(F.count("*").alias("n"))
    starts = cells.select("shard", "cell", (F.sum("n").over(W.partitionBy("shard").orderBy("cell")) - F.col("n")).alias("start"))  # a row a shard and cell
    again = sent.withColumn("again", F.row_number().over(W.partitionBy("shard", "cell").orderBy(draw("again"), "key")))
    out = again.join(starts, ["shard", "cell"])
    return out.select(*(F.col(f"row.`{c}`") for c in kept), "shard", (F.col("start") + F.col("again") - 1).cast("long").alias("slot"))


def write_shards(df: DataFrame, path: str, shards: int, key: list, seed: int = 0) -> None:
    """One folder a shard, its files in slot order one after the other."""
    out = shard(df, shards, key, seed)
    out.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    text = text_or_empty()
    rows = docs.select("doc_id", (F.octet_length("text").cast("long")).alias("b"), F.crc32(text.cast("binary")).alias("text_crc32"))
    rows = rows.select("doc_id", (F.coalesce("b", F.lit(0)) + 8).alias("size"), "text_crc32")
    out = shard(rows, 24, [F.col("doc_id"), F.col("text_crc32"), F.col("size")], seed=1)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
