"""Exact n-gram Jaccard join as a blocked sparse product of the document by n-gram matrix.

Rows of the matrix are distinct shingle sets (documents with equal sets are one row, one
class), columns are shingles.  Only a part of each row takes part in the product: under one
global order of the shingles, two sets of similarity t share one of their first
n - ceil(t n) + 1, so those suffice.  The order puts shingles that are common in a sample
of the documents last and is otherwise a hash order; any order gives the same result.

A column is a block of rows that may be similar.  Blocks are worked off in two steps, so
that no block's pairs are ever written out:
1. Each row is paired with the block's first row only (its pivot); the pairs' sizes and
   512-bit sketches bound the overlap they can have, pairs below the bound go, the rest
   is counted exactly.  The links found join most rows of a large block.
   In blocks that stay divided this is repeated with other pivots.
2. In blocks whose rows are still in several components, rows of different components
   are paired, under the same bounds inside the join, and counted exactly.
Components of all links are then those of the whole join: a pair left out is either below
the bound or already connected.

Defined results.  Texts without words, and null ones, have empty sets and are linked with
nothing.  A null doc_id names a component only if it has no other.  Rows that repeat get the same
result.  An empty table gives no rows.  Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow_text import map_arrow, slices, small_batches, utf8
from .common import Scratch, components, keepers, relieve, row_key, small
from .shingles import shingle_set, word_hashes

SHINGLE, PERCENT = 5, 75
#: One document in so many is in the sample that orders the shingles; its count from which a shingle is common; how many of those are used.
SAMPLE_ONE_IN, COMMON, MAX_COMMON = 8, 2, 500_000
SKETCH = 8  # words of 64 bits
#: A second, wider sketch, read for single pairs only: (size above which, words).
WIDE = [(0, 32), (512, 64), (4096, 512)]
#: Smallest hashes of a set's part of the product that its rows carry, so that a pair is written once and not once a shingle.
#: And how often rows of open blocks are paired with a pivot chosen anew, at most.
HEAD, ROUNDS = 4, 3


def sets_of(part: pa.RecordBatch, k: int) -> Iterator[np.ndarray]:
    buf, off = utf8(part.column(part.schema.get_field_index("text")))
    hashes, first = word_hashes(buf, off)
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        yield shingle_set(hashes[a:b], k)


def digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def sketch(s: np.ndarray, words: int) -> np.ndarray:
    bits = np.zeros(64 * words, dtype=np.uint8)
    if words:
        bits[s & (64 * words - 1)] = 1
    return np.packbits(bits).view(np.int64)


def lists(values: list[np.ndarray]) -> pa.ListArray:
    off = np.concatenate(([0], np.cumsum([len(v) for v in values]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(off), pa.array(np.concatenate(values) if values else np.zeros(0, dtype=np.int64)))


def common_shingles(docs: DataFrame, k: int) -> np.ndarray:
    """Sorted hashes of the shingles that are common in the sample (chosen by a hash of the row); the most common MAX_COMMON at most."""
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                seen, n = np.unique(np.concatenate([*sets_of(part, k), np.zeros(0, dtype=np.int64)]), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(seen), pa.array(n.astype(np.int64))], ["shingle", "n"])

    sample = docs.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(SAMPLE_ONE_IN)) == 0).select("text")
    rows = map_arrow(sample, work, "shingle bigint, n bigint").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") >= COMMON).orderBy(F.desc("n"), "shingle").limit(MAX_COMMON).select("shingle")
    return np.sort(rows.toArrow().column(0).to_numpy())


def rows_of(docs: DataFrame, k: int, percent: int, common: np.ndarray) -> DataFrame:
    """(doc_id, key, fp, n, prefix, sketch, wide): fp identifies the set, sketches have a bit for each shingle."""
    shipped = docs.sparkSession.sparkContext.broadcast(common)  # MAX_COMMON numbers at most

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = shipped.value
        for batch in batches:
            for part in slices(batch, "text"):
                fps, ns, prefixes, sketches, wides = [], [], [], [], []
                for s in sets_of(part, k):
                    n = len(s)
                    head = n + (-percent * n // 100) + 1 if n else 0
                    is_late = late[np.minimum(np.searchsorted(late, s), len(late) - 1)] == s if len(late) else np.zeros(n, dtype=bool)
                    early = s[~is_late][:head]
                    prefixes.append(np.concatenate((early, s[is_late][: head - len(early)])))
                    sketches.append(sketch(s, SKETCH))
                    wides.append(sketch(s, max([w for least, w in WIDE if n > least], default=0)))
                    ns.append(n)
                    fps.append(digest(s))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(fps, pa.binary()), pa.array(ns, pa.int64()), lists(prefixes), lists(sketches), lists(wides)], ["doc_id", "key", "fp", "n", "prefix", "sketch", "wide"])

    return map_arrow(docs.select("doc_id", "text", row_key().alias("key")), work, "doc_id bigint, key bigint, fp binary, n bigint, prefix array<bigint>, sketch array<bigint>, wide array<bigint>")


def full_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(rid, shingles) for wanted rows (rid, key, fp); fp tells rows apart that share a key."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                sets = list(sets_of(part, k))
                right = [digest(s) == fp for s, fp in zip(sets, part.column(1).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), lists(sets)], ["rid", "shingles"]).filter(pa.array(right))

    rows = docs.select(row_key().alias("key"), "text").join(small(wanted), "key").select("rid", "fp", "text")
    return map_arrow(rows, work, "rid bigint, shingles array<bigint>").dropDuplicates(["rid"])


def possible(percent: int) -> Column:
    """Whether the sizes and sketches of the sets a and b leave room for the similarity."""
    room = lambda x, y: F.col(f"{x}.n") - sum((F.bit_count(F.col(f"{x}.w{i}").bitwiseAND(F.bitwise_not(F.col(f"{y}.w{i}")))) for i in range(1, SKETCH)), F.bit_count(F.col(f"{x}.w0").bitwiseAND(F.bitwise_not(F.col(f"{y}.w0")))))
    return enough(F.least(room("a", "b"), room("b", "a")), F.col("a.n"), F.col("b.n"), percent)


def still_possible(x: str, y: str, percent: int) -> Column:
    """The same by the wide sketches, for sets that have such of one width."""
    missing = lambda p, q: F.aggregate(F.zip_with(f"{p}.wide", f"{q}.wide", lambda u, v: F.bit_count(u.bitwiseAND(F.bitwise_not(v)))), F.lit(0), lambda u, v: u + v)
    room = F.least(F.col(f"{x}.n") - missing(x, y), F.col(f"{y}.n") - missing(y, x))
    return (F.size(f"{x}.wide") == 0) | (F.size(f"{x}.wide") != F.size(f"{y}.wide")) | enough(room, F.col(f"{x}.n"), F.col(f"{y}.n"), percent)


def enough(overlap: Column, a: Column, b: Column, percent: int) -> Column:
    return (100 + percent) * overlap >= percent * (a + b)


def counted(scratch: Scratch, docs: DataFrame, rows: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (x, y) whose sets are similar: those that the wide sketches leave possible, by exact overlap."""
    a, b = (rows.select(F.col("rid").alias(v), F.struct("n", "wide").alias(f"w{v}")) for v in "xy")
    pairs = pairs.join(a, "x").join(b, "y").where(still_possible("wx", "wy", percent))
    pairs = scratch.table(pairs.select("x", "y"), "pairs")
    wanted = pairs.select(F.col("x").alias("rid")).unionByName(pairs.select(F.col("y").alias("rid"))).distinct()
    wanted = scratch.table(wanted.join(rows.select("rid", "key", "fp"), "rid"), "wanted")
    sets = scratch.table(full_sets(docs, wanted, k), "sets")
    both = pairs.join(sets.select(F.col("rid").alias("x"), F.col("shingles").alias("sx")), "x").join(sets.select(F.col("rid").alias("y"), F.col("shingles").alias("sy")), "y")
    return scratch.table(both.where(enough(F.size(F.array_intersect("sx", "sy")), F.size("sx"), F.size("sy"), percent)).select("x", "y"), "links")


def runs(postings: DataFrame) -> DataFrame:
    """(token, rid, pivot) of the columns that have several rows: each column's rows stream by in order, none is gathered."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last row seen and its run's pivot, not yet sent if it is alone so far
        for batch in batches:
            if not batch.num_rows:
                continue
            t, r = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            if held is not None:
                t, r = np.concatenate(([held[0]], t)), np.concatenate(([held[1]], r))
            new = np.concatenate(([True], t[1:] != t[:-1]))
            heads = np.flatnonzero(new)
            pivot = np.repeat(r[heads], np.diff(np.append(heads, len(t))))
            alone = new & np.concatenate((new[1:], [False]))
            send = ~alone
            send[-1] &= not new[-1]
            if held is not None and held[0] == t[0]:
                pivot[: np.append(heads, len(t))[1]] = held[2]
                send[0] = (len(t) > 1 and not new[1]) and not held[3]
            yield pa.RecordBatch.from_arrays([pa.array(t[send]), pa.array(r[send]), pa.array(pivot[send])], ["token", "rid", "pivot"])
            held = (t[-1], r[-1], pivot[-1], bool(send[-1]) or (len(t) == 1 and held is not None and held[3]))

    return map_arrow(postings.repartition("token").sortWithinPartitions("token", "rid"), work, "token bigint, rid bigint, pivot bigint")


def classes(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id: the smallest doc_id that links reach."""
    return components_of(docs, k, percent).select("doc_id", "n_shingles", "component_id")


def components_of(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The same with each row's key and c, its component's number (null for empty sets)."""
    scratch = Scratch(docs.sparkSession, "jaccard")
    # Stored, so that row numbers given on the way stay what they are.
    with small_batches(docs.sparkSession):
        rows = scratch.table(rows_of(docs, k, percent, common_shingles(docs, k)).withColumn("rid", F.monotonically_increasing_id()), "rows")
    reps = rows.where("n > 0").groupBy("fp").agg(F.min(F.struct("rid", "doc_id")).alias("r"), F.min("doc_id").alias("least"))
    reps = scratch.table(reps.select("fp", F.col("r.rid").alias("rid"), F.col("r.doc_id").alias("doc_id"), "least"), "reps")
    # Rows that are not their class's: few as a rule, so that the others need not be shuffled to lose them.
    copies = scratch.table(rows.where("n > 0").select("rid", "fp").join(reps.select("rid"), "rid", "left_anti").select("rid"), "copies")
    own = rows.where("n > 0").join(small(copies), "rid", "left_anti")
    sizes = own.select("rid", "n", *(F.col("sketch")[i].alias(f"w{i}") for i in range(SKETCH)), F.slice(F.array_sort("prefix"), 1, HEAD).alias("head"))

    columns = scratch.table(runs(own.select(F.explode("prefix").alias("token"), "rid")), "columns")
    star = columns.where("rid <> pivot").select(F.col("rid").alias("x"), F.col("pivot").alias("y")).distinct()
    star = star.join(sizes.alias("a"), F.col("x") == F.col("a.rid")).join(sizes.alias("b"), F.col("y") == F.col("b.rid")).where(possible(percent)).select("x", "y")
    links = counted(scratch, docs, rows, star, k, percent)

    for again in range(1, ROUNDS + 1):
        relieve(docs.sparkSession)
        found = components(scratch, links, "x", "y")
        known = own.select("rid", "n").join(found.withColumnRenamed("v", "rid"), "rid", "left").withColumn("c", F.coalesce("c", "rid"))
        labelled = scratch.table(columns.select("token", "rid").join(known, "rid"), "labelled", at := [])
        # Blocks with rows of several components; of two rows that their sizes part, none are.
        open_ = labelled.groupBy("token").agg(F.count("*").alias("m"), F.min("c").alias("lo"), F.max("c").alias("hi"), F.min("n").alias("short"), F.max("n").alias("long"), F.min_by(F.struct("rid", "c"), F.xxhash64("rid", "token", F.lit(again))).alias("pivot"))
        open_ = open_.where((F.col("lo") != F.col("hi")) & ((F.col("m") > 2) | (100 * F.col("short") >= percent * F.col("long")))).select("token", "pivot")
        if again == ROUNDS:
            break
        # In large blocks rows meet another pivot: most of a group of near copies joins before any pair of its is looked at.
        star = labelled.join(open_, "token").where("c <> pivot.c").select(F.col("rid").alias("x"), F.col("pivot.rid").alias("y")).distinct()
        star = star.join(sizes.alias("a"), F.col("x") == F.col("a.rid")).join(sizes.alias("b"), F.col("y") == F.col("b.rid")).where(possible(percent)).select("x", "y")
        new = counted(scratch, docs, rows, star, k, percent)
        scratch.drop(at[0])
        if new.isEmpty():
            continue
        links = links.unionByName(new)
    open_rows = scratch.table(labelled.join(open_.select("token"), "token", "left_semi").drop("n").join(sizes, "rid"), "open")
    # A pair whose heads meet is taken in the block of the first shingle they share, any other in all its blocks.
    meet = F.get(F.array_intersect("a.head", "b.head"), F.lit(0))
    once = meet.isNull() | (meet == F.col("a.token"))
    rest = open_rows.alias("a").join(open_rows.alias("b"), (F.col("a.token") == F.col("b.token")) & (F.col("a.rid") < F.col("b.rid")) & (F.col("a.c") != F.col("b.c")) & enough(F.least("a.n", "b.n"), F.col("a.n"), F.col("b.n"), percent) & possible(percent) & once)
    more = counted(scratch, docs, rows, rest.select(F.col("a.rid").alias("x"), F.col("b.rid").alias("y")).distinct(), k, percent)

    final = components(scratch, links.unionByName(more), "x", "y")
    named = reps.select("fp", "rid", "least").join(final.withColumnRenamed("v", "rid"), "rid", "left").withColumn("c", F.coalesce("c", "rid"))
    lowest = named.groupBy("c").agg(F.min("least").alias("component"))
    named = scratch.table(named.join(lowest, "c").select("fp", "c", "component"), "components")
    return rows.join(named, "fp", "left").select("doc_id", "key", "c", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))


def survivors(docs: DataFrame) -> DataFrame:
    """One document of each component (the smallest doc_id), with all its columns."""
    scratch = Scratch(docs.sparkSession, "jaccard")
    rows = scratch.table(components_of(docs).groupBy("doc_id", "key", "c").agg(F.count("*").alias("n")), "members")
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")
    first = rows.where("c is not null").groupBy("c").agg(F.min(place).alias("first"), F.count("*").alias("m")).where("m > 1").drop("m")
    verdicts = rows.join(first, "c", "left").select("doc_id", "key", F.coalesce(place != F.col("first"), F.lit(False)).alias("gone"), "n")
    return keepers(docs, row_key(), scratch.table(verdicts.where("gone or n > 1"), "verdicts"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^ 	-
]+') AS words FROM documents
), s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 5 THEN [array_to_string(words, ' ')]
    ELSE list_transform(range(1, len(words) - 3), lambda i: array_to_string(list_slice(words, i, i + 4), ' ')) END) AS shingle FROM w
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), pairs AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id
), links AS (
  SELECT x, y FROM pairs JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * o >= 75 * (p.n + q.n - o)
), reach AS (
  SELECT x AS v, y AS r FROM links UNION SELECT reach.v, links.y FROM reach JOIN links ON links.x = reach.r
), least AS (SELECT v, min(r) AS r FROM reach GROUP BY v)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, least(d.doc_id, coalesce(least.r, d.doc_id)) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN least ON least.v = d.doc_id
"""
