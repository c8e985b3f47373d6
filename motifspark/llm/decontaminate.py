"""Benchmark decontamination by size-partitioned MinHash containment search.

A test item is the query, a document the large set.  Items are partitioned by the size of
their shingle sets (powers of two).  Each item of a partition keeps a bottom-k MinHash
sketch, its k smallest shingle hashes, with k = u / 4 + 1 for the partition's upper size u:
an item of which three quarters of the shingles lie in a document has at least one of
those k in it, so looking up the sketches loses no document.  Documents that hold a sketch
value are candidates and are verified by exact containment of the item's shingles, as text.

Words are runs of letters and figures in lower case; shingles take five words, an item
with fewer words is one shingle of them all (documents are then looked up with shingles
of that length too).

Defined results.  Empty and null items match nothing, empty and null documents hold
nothing.  Rows of one doc_id count as one document if any of them matches; rows without
doc_id are not reported.  ``survivors`` judges each row by its own text, whatever its doc_id.  Items that repeat
are searched once an item_id; of texts that share one, each is an item of its own.  Empty tables
give no rows; extra columns are ignored by ``matches`` and kept by ``survivors``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, small, text_or_empty, without

SHINGLE, PERCENT = 5, 75


def words(text: str = "text") -> Column:
    return F.filter(F.split(F.regexp_replace(F.lower(text_or_empty(text)), r"[^\p{L}\p{N}]+", " "), " "), lambda w: w != "")


def shingles(column: str, size: int, as_text: bool = False) -> Column:
    """Shingles of one size of an array of words, hashed or as text; none where the words are fewer.

    Words are taken one by one: slice() would copy the whole array for every shingle.
    """
    of = (lambda w: F.concat_ws(" ", *w)) if as_text else (lambda w: F.xxhash64(*w))
    every = F.transform(F.sequence(F.lit(0), F.size(column) - size), lambda i: of([F.get(F.col(column), i + j) for j in range(size)]))
    return F.when(F.size(column) >= size, every).otherwise(F.array().cast("array<string>" if as_text else "array<bigint>"))


def by_size(column: str, size: str, as_text: bool) -> Column:
    """The shingles of the size that another column names."""
    out = F.when(F.col(size) == SHINGLE, shingles(column, SHINGLE, as_text))
    for s in range(1, SHINGLE):
        out = out.when(F.col(size) == s, shingles(column, s, as_text))
    return out


def items_of(benchmark: DataFrame) -> DataFrame:
    """(item_id, size, texts, hashes, n): shingle size, distinct shingles as text and hashed, and how many."""
    d = benchmark.select("item_id", words().alias("w")).where(F.size("w") > 0).withColumn("size", F.least(F.size("w"), F.lit(SHINGLE)))
    d = d.select("item_id", "size", F.array_distinct(by_size("w", "size", True)).alias("texts"), F.array_distinct(by_size("w", "size", False)).alias("hashes"))
    return d.dropDuplicates(["item_id", "texts"]).withColumn("n", F.size("texts"))


def sketches(items: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(h, item): each item's bottom-k sketch, k by its size partition."""
    upper = F.pow(F.lit(2), F.ceil(F.log2("n"))).cast("int")
    k = (upper * (100 - percent) / 100).cast("int") + 1
    return items.select("item", F.explode(F.slice(F.array_sort("hashes"), 1, k)).alias("h")).distinct()


def matches(docs: DataFrame, benchmark: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(doc_id, item_id, n_shared, n_item): items of which the document holds at least ``percent`` of the shingles."""
    scratch = Scratch(docs.sparkSession, "decontaminate")
    # Stored, so that item numbers stay what they are: an item_id may be null, or repeat with another text.
    items = scratch.table(items_of(benchmark).withColumn("item", F.monotonically_increasing_id()), "items")
    sizes = sorted(r[0] for r in items.select("size").distinct().collect())  # five at most
    if not sizes:
        return docs.sparkSession.createDataFrame([], "doc_id bigint, item_id bigint, n_shared int, n_item int")
    sketch = scratch.table(sketches(items, percent), "sketches")
    hashed = docs.where("doc_id is not null").select("doc_id", words().alias("w")).select("doc_id", F.concat(*(shingles("w", s) for s in sizes)).alias("hs"))
    # explode_outer and the late filter below: a filter pushed under the split into words would split again for every shingle.
    found = hashed.select("doc_id", F.explode_outer("hs").alias("h")).join(small(sketch), "h").select("doc_id", "item").distinct()
    found = scratch.table(found, "candidates")
    checked = docs.select("doc_id", "text").join(small(found), "doc_id").select("doc_id", "item", words().alias("w")).join(small(items.drop("hashes"), width=F.aggregate("texts", F.lit(0).cast("long"), lambda n, t: n + F.octet_length(t) + 16)), "item")
    held = by_size("w", "size", True)
    checked = checked.select("doc_id", "item_id", F.size(F.array_intersect("texts", held)).alias("n_shared"), F.col("n").alias("n_item"))
    checked = checked.where(100 * F.col("n_shared") >= percent * F.col("n_item"))
    return checked.groupBy("doc_id", "item_id").agg(F.max(F.struct("n_shared", "n_item")).alias("m")).select("doc_id", "item_id", "m.n_shared", "m.n_item")


def survivors(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that hold no item, with all their columns."""
    return without(docs, lambda d: matches(d, benchmark))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return matches(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}]+') AS w FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}]+') AS w FROM benchmark
), items AS (
  SELECT DISTINCT item_id, least(len(w), 5) AS size,
         unnest(list_transform(range(1, len(w) - least(len(w), 5) + 2), lambda i: array_to_string(list_slice(w, i, i + least(len(w), 5) - 1), ' '))) AS shingle
  FROM b WHERE len(w) > 0
), sizes AS (SELECT DISTINCT size FROM items
), held AS (
  SELECT DISTINCT doc_id, size, unnest(list_transform(range(1, len(w) - size + 2), lambda i: array_to_string(list_slice(w, i, i + size - 1), ' '))) AS shingle
  FROM d, sizes WHERE len(w) >= size
), n AS (SELECT item_id, count(*) AS n_item FROM items GROUP BY item_id
), shared AS (
  SELECT doc_id, item_id, count(*) AS n_shared FROM held JOIN items USING (size, shingle) GROUP BY ALL
)
SELECT doc_id, item_id, CAST(n_shared AS INTEGER) AS n_shared, CAST(n_item AS INTEGER) AS n_item
FROM shared JOIN n USING (item_id) WHERE 100 * n_shared >= 75 * n_item
"""
