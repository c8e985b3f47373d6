"""Repeated passages by a sparse suffix array.

A passage of at least LEAST words that also stands in another document is found.  Of each
text only suffixes at minimisers are retained: among the LEAST - HEAD + 1 runs of HEAD
words inside any LEAST words, the one of the smallest hash.  Any two copies of a passage
retain the same suffixes in it.  The retained suffixes are sorted by their first HEAD words
(by hash: any order of words will do) and neighbours are compared; suffixes whose first
HEAD words no other document has are dropped, which is most of them.  Around those that
stay the match is extended to the left and to the right: every stretch of LEAST words of
which the suffix is the minimiser is sorted in the same way and compared with its
neighbours, and stretches that another document has are joined to passages.

Before each sort a worker combines what it has seen: a key that two of its documents hold
is settled at once, and one witness goes out for the others, so a passage that a third of
all documents share is a few rows a worker.  Sorted rows stream by; none of a key's rows
are gathered.

Words are runs of bytes without ASCII white space, A-Z in lower case, compared by 64-bit
hashes.

Defined results.  Null, empty and shorter texts have no passage.  Rows of one doc_id are
one document: a passage that only repeats inside it does not count.  Rows without doc_id
are left out.  An empty table gives no rows.  Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow_text import map_arrow, slices, small_batches, utf8
from .common import Scratch
from .shingles import grams, mix, word_hashes

LEAST, HEAD = 50, 25
#: What a row says: its key must be looked up; its key is held by two documents; it is settled already.
ASKS, WITNESS, SETTLED = 0, 1, 2
ROWS = "key bigint, kind int, doc_id bigint, name bigint"


def window_minima(values: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w neighbours, by doubling."""
    out, have = values, 1
    while have < w:
        step = min(have, w - have)
        out, have = np.minimum(out[:-step], out[step:]), have + step
    return out


def minimisers(words: np.ndarray, least: int, head: int) -> np.ndarray:
    """For each stretch of ``least`` words (there must be one) the hash of its minimiser."""
    return window_minima(grams(words, head), least - head + 1).view(np.int64)


def combined(key: np.ndarray, doc: np.ndarray, name: np.ndarray) -> pa.RecordBatch:
    """Rows of one worker's share: keys that two documents hold are settled (and dealt evenly), with one witness each."""
    order = np.lexsort((doc, key))
    key, doc, name = key[order], doc[order], name[order]
    heads = np.flatnonzero(np.concatenate((np.ones(min(1, len(key)), dtype=bool), key[1:] != key[:-1])))
    sizes = np.diff(np.append(heads, len(key)))
    shared = doc[heads] != doc[heads + sizes - 1]
    done = np.repeat(shared, sizes)
    spread = mix(doc.view(np.uint64) + mix(name.view(np.uint64))).view(np.int64)
    w = heads[shared]
    columns = (
        np.concatenate((np.where(done, spread, key), key[w])),
        np.concatenate((np.where(done, SETTLED, ASKS), np.full(len(w), WITNESS))).astype(np.int32),
        np.concatenate((doc, doc[w])),
        np.concatenate((name, name[w])),
    )
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["key", "kind", "doc_id", "name"])


class Neighbours:
    """Sorted rows stream by; those whose key another document holds come out.

    A run of equal keys may go on in the next batch.  Until a second document (or a
    witness, which sorts first) has come, the rows of the run's first document are held.
    """

    def __init__(self):
        self.key, self.doc, self.known, self.held = None, None, False, []

    def push(self, key: np.ndarray, kind: np.ndarray, doc: np.ndarray, name: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        out = [(doc[kind == SETTLED], name[kind == SETTLED])]
        open_ = kind != SETTLED
        key, kind, doc, name = key[open_], kind[open_], doc[open_], name[open_]
        if len(key):
            heads = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            low, high = np.minimum.reduceat(doc, heads), np.maximum.reduceat(doc, heads)
            shared = (low != high) | (np.maximum.reduceat(kind, heads) == WITNESS)
            goes_on = self.key == key[0]
            if goes_on:
                shared[0] |= self.known or low[0] != self.doc
                if shared[0]:
                    out += self.held
            verdict = np.repeat(shared, np.diff(np.append(heads, len(key)))) & (kind == ASKS)
            out.append((doc[verdict], name[verdict]))
            last = heads[-1]
            before = self.held if goes_on and len(heads) == 1 else []
            self.key, self.doc, self.known = key[-1], doc[-1], bool(shared[-1])
            self.held = [] if self.known else [*before, (doc[last:], name[last:])]
        return np.concatenate([d for d, _ in out]), np.concatenate([n for _, n in out])


def settled(rows: DataFrame) -> DataFrame:
    """(doc_id, name) of the rows whose key another document holds."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stream = Neighbours()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in stream.push(*(batch.column(i).to_numpy() for i in range(4)))], ["doc_id", "name"])

    return map_arrow(rows.repartition("key").sortWithinPartitions("key", F.desc("kind"), "doc_id"), work, "doc_id bigint, name bigint")


def anchors(docs: DataFrame, least: int, head: int) -> DataFrame:
    """Rows of the retained suffixes, named by the hash of their first words."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                buf, off = utf8(part.column(1))
                hashes, first = word_hashes(buf, off)
                keys, docs_ = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)]
                for d, a, b in zip(part.column(0).to_pylist(), first[:-1].tolist(), first[1:].tolist(), strict=True):
                    if b - a >= least:
                        keys.append(np.unique(minimisers(hashes[a:b], least, head)))
                        docs_.append(np.full(len(keys[-1]), d))
                key = np.concatenate(keys)
                yield combined(key, np.concatenate(docs_), key)

    return map_arrow(docs.where("doc_id is not null").select("doc_id", "text"), work, ROWS)


def stretches(docs: DataFrame, least: int, head: int) -> DataFrame:
    """docs: rows (doc_id, text, keys).  Rows of the stretches of ``least`` words whose minimiser is in keys, named by their first word's number."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                buf, off = utf8(part.column(1))
                hashes, first = word_hashes(buf, off)
                keys, docs_, starts = [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)], [np.zeros(0, dtype=np.int64)]
                wanted = part.column(2)
                for d, (doc, a, b) in enumerate(zip(part.column(0).to_pylist(), first[:-1].tolist(), first[1:].tolist(), strict=True)):
                    if b - a >= least:
                        at = np.flatnonzero(np.isin(minimisers(hashes[a:b], least, head), wanted[d].values.to_numpy()))
                        keys.append(grams(hashes[a:b], least).view(np.int64)[at])
                        docs_.append(np.full(len(at), doc))
                        starts.append(at)
                yield combined(np.concatenate(keys), np.concatenate(docs_), np.concatenate(starts))

    return map_arrow(docs.select("doc_id", "text", "keys"), work, ROWS)


def joined(marks: DataFrame, least: int) -> DataFrame:
    """(doc_id, n_passages, n_words, passages) from rows (doc_id, starts of repeated stretches)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, words, said = [], [], []
            for d in range(batch.num_rows):
                s = np.unique(batch.column(1)[d].values.to_numpy())
                cut = np.flatnonzero(s[1:] > s[:-1] + least)
                a, b = s[np.concatenate(([0], cut + 1))], s[np.concatenate((cut, [len(s) - 1]))] + least
                counts.append(len(a))
                words.append(int((b - a).sum()))
                said.append(",".join(f"{x}:{y}" for x, y in zip(a.tolist(), b.tolist(), strict=True)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(words, pa.int64()), pa.array(said, pa.string())], ["doc_id", "n_passages", "n_words", "passages"])

    return marks.groupBy("doc_id").agg(F.collect_list("name").alias("starts")).mapInArrow(work, "doc_id bigint, n_passages bigint, n_words bigint, passages string")  # a list is as long as its document at most


def passages(docs: DataFrame, least: int = LEAST, head: int = HEAD) -> DataFrame:
    """Documents with repeated passages: doc_id, n_passages, n_words in them, passages as start:end in words, comma-joined."""
    scratch = Scratch(docs.sparkSession, "passages")
    with small_batches(docs.sparkSession):
        keys = scratch.table(settled(anchors(docs, least, head)).groupBy("doc_id").agg(F.collect_set("name").alias("keys")), "suffixes")
    near = docs.select("doc_id", "text").join(keys, "doc_id")
    return joined(settled(stretches(near, least, head)), least)


def without(docs: DataFrame, found: DataFrame) -> DataFrame:
    """docs with the repeated passages cut out of their texts (words are joined by single spaces there)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, spans in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                words = (text or "").encode().split()
                for span in reversed(spans.split(",")):
                    a, b = map(int, span.split(":"))
                    del words[a:b]
                texts.append(b" ".join(words).decode())
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()), batch.column(2)], ["text", "_row"])

    # The other columns travel as one struct: no name of the caller's meets one of ours.
    others = [c for c in docs.columns if c != "text"]
    rows = docs.select("doc_id", "text", F.struct(*(F.col(f"`{c}`") for c in others)).alias("_row"))
    hit = rows.join(found.select("doc_id", "passages"), "doc_id").select("text", "passages", "_row")
    cut = map_arrow(hit, work, f"text string, _row {rows.schema['_row'].dataType.simpleString()}")
    own = [F.col("text") if c == "text" else F.col(f"_row.`{c}`") for c in docs.columns]
    left = rows.join(found.select("doc_id"), "doc_id", "left_anti")
    return left.select(*own).unionByName(cut.select(*own))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


SQL = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^ 	-
]+') AS words FROM documents
), p AS (
  SELECT doc_id, words, unnest(range(1, len(words) - 48)) AS i FROM w WHERE len(words) >= 50
), s AS (
  SELECT doc_id, i - 1 AS s, hash(list_slice(words, i, i + 49)) AS h FROM p
), r AS (
  SELECT h FROM s GROUP BY h HAVING min(doc_id) <> max(doc_id)
), m AS (
  SELECT DISTINCT doc_id, s FROM s WHERE h IN (SELECT h FROM r)
), g AS (
  SELECT doc_id, s, CASE WHEN s - lag(s) OVER (PARTITION BY doc_id ORDER BY s) <= 50 THEN 0 ELSE 1 END AS fresh FROM m
), k AS (
  SELECT doc_id, s, sum(fresh) OVER (PARTITION BY doc_id ORDER BY s) AS passage FROM g
), spans AS (
  SELECT doc_id, min(s) AS a, max(s) + 50 AS b FROM k GROUP BY doc_id, passage
)
SELECT doc_id, count(*) AS n_passages, CAST(sum(b - a) AS BIGINT) AS n_words, string_agg(a || ':' || b, ',' ORDER BY a) AS passages FROM spans GROUP BY doc_id
"""
