"""Packing by cutting-stock column generation.

Documents are tokenised and cut into pieces of at most one sequence.  The histogram of
piece lengths (in classes of GRAIN tokens, rounded up) is the demand of a cutting-stock
problem whose stock is the sequence.  Its linear program is solved on the driver by
column generation: a revised simplex over patterns, priced by an unbounded knapsack
(dynamic programming over the capacity).  Patterns are rounded down; what is left is
packed first-fit decreasing.  Both the program and the patterns are bounded by the number
of classes, not by the data.

Pieces are ranked inside their class (gapless, by hashed cells, no task holds a class),
and ranks are dealt to the copies of the patterns by arithmetic, so the assignment is a
join with a small table.

Token ids of a text are those of its white-space separated words, one after the other
(the tokenizer never joins across ASCII white space); a worker keeps a table of words' ids
of fixed size, in which words are compared byte by byte.

Defined results.  Null and empty texts are the end id alone.  Repeated rows are packed
one by one, also under one doc_id or none.  A text of any length is cut.  An empty table
gives no rows.  Extra columns are ignored.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .arrow_text import map_arrow, per_process, slices, small_batches, utf8
from .common import Scratch, local_rows, ranked
from .shingles import LOWER, span_hashes, word_spans

LENGTH, GRAIN, END = 4096, 16, 2
LAST = END.to_bytes(4, "little")
#: Places of the table of known words, room for their ids and for their bytes; longer words aren't kept.
PLACES, ROOM, LONG_WORD, LINE = 1 << 20, 4 << 20, 48, 200
#: Bytes of text and new words that a worker encodes together; both bound its memory.
ENCODE_BYTES, ENCODE_WORDS = 2 << 20, 4_000
RANK_ROWS = 50_000
MARK, ALNUM = np.zeros(256, dtype=bool), np.zeros(256, dtype=bool)
MARK[list(b".,;:!?")] = True
ALNUM[list(b"0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ")] = True
#: Fixed value, as it stands in a tokenizer's JSON: letters, single figures and runs of marks are parted.
PARTED = json.dumps(r"[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")[1:-1]


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def spread(start: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The indices of the runs start[i] .. start[i] + sizes[i], one after the other."""
    ends = np.cumsum(sizes)
    return np.repeat(start - (ends - sizes), sizes) + np.arange(int(sizes.sum()))


def same_bytes(a: np.ndarray, a_at: np.ndarray, a_size: np.ndarray, b: np.ndarray, b_at: np.ndarray, b_size: np.ndarray, most: int = 1 << 18) -> np.ndarray:
    """Whether the runs of bytes are equal, pair by pair; some pairs at a time."""
    out = a_size == b_size
    todo = np.flatnonzero(out & ((a_at != b_at) | (a is not b)) & (a_size > 0))
    heads, lo = np.concatenate(([0], np.cumsum(a_size[todo]))), 0
    while lo < len(todo):
        hi = max(lo + 1, int(np.searchsorted(heads, heads[lo] + most, "right")) - 1)
        k = todo[lo:hi]
        equal = a[spread(a_at[k], a_size[k])] == b[spread(b_at[k], a_size[k])]
        if not equal.all():
            out[k] = np.logical_and.reduceat(equal, heads[lo:hi] - heads[lo])
        lo = hi
    return out


class Encoder:
    """Token ids of many texts, word by word, with a table of known words whose size is fixed.

    A word's 64-bit hash names its place in the table; a hit counts only if the word's bytes are those
    kept there, so words that share a hash are told apart.  A word enters when it is met in a second batch
    and its place is free; when the room for ids or bytes is used up the table starts anew.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # the cores are Spark's
        from tokenizers import Tokenizer

        self.t = Tokenizer.from_file(path)
        self.ends = np.zeros(self.t.get_vocab_size(), dtype=bool)
        self.ends[[i for token, i in self.t.get_vocab().items() if token.endswith("</w>")]] = True
        said = json.loads(self.t.to_str())
        self.folds = '"Lowercase"' in json.dumps(said.get("normalizer"))
        self.splits = PARTED in json.dumps(said.get("pre_tokenizer"), ensure_ascii=False)
        self.size, self.bytes = np.zeros(PLACES, dtype=np.uint8), np.zeros(PLACES, dtype=np.uint8)
        self.at, self.byte_at = np.zeros(PLACES, dtype=np.int32), np.zeros(PLACES, dtype=np.int32)
        self.ids, self.letters = np.zeros(ROOM, dtype="<u4"), np.zeros(ROOM, dtype=np.uint8)
        self.seen = np.zeros(1 << 22, dtype=bool)
        self.renew()

    def renew(self) -> None:
        self.bytes[:] = 0  # no word has no bytes
        self.used = self.byte_used = 0

    def _learn(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of new words, and how many each has.

        Letters, with one mark after them or none, are one or two tokens of the pre-tokeniser, so such
        words are encoded in long lines and cut where a word's last id stands; others go one by one.
        """
        flats, counts = [np.zeros(0, dtype="<u4")], [np.zeros(0, dtype=np.int64)]
        for k in range(0, len(words), ENCODE_WORDS):
            said = [w.decode() for w in words[k : k + ENCODE_WORDS]]
            runs = np.array([1 if w.isalpha() else 2 if w[-1] in ".,;:!?" and w[:-1].isalpha() else 0 for w in said])
            plain = np.flatnonzero(runs)
            if len(plain):
                line = [said[i] for i in plain.tolist()]
                lines = self.t.encode_batch_fast([" ".join(line[i : i + LINE]) for i in range(0, len(line), LINE)], add_special_tokens=False)
                ids = np.array(list(chain.from_iterable(e.ids for e in lines)), dtype="<u4")
                last = np.flatnonzero(self.ends[ids])
                if len(last) == runs.sum():
                    cut = np.concatenate(([0], last[np.cumsum(runs[plain]) - 1] + 1))
                else:
                    plain = plain[:0]
            rest = np.setdiff1d(np.arange(len(said)), plain)
            found = self.t.encode_batch_fast([said[i] for i in rest.tolist()], add_special_tokens=False) if len(rest) else []
            flat = [e.ids for e in found]
            sizes = np.zeros(len(said), dtype=np.int64)
            other = np.array(list(chain.from_iterable(flat)), dtype="<u4")
            sizes[rest] = list(map(len, flat))
            if len(plain):
                sizes[plain] = np.diff(cut)
                pool, start = np.concatenate((ids, other)), np.zeros(len(said), dtype=np.int64)
                start[plain], start[rest] = cut[:-1], len(ids) + np.concatenate(([0], np.cumsum(sizes[rest])))[:-1]
                ends = np.cumsum(sizes)
                other = pool[np.repeat(start - (ends - sizes), sizes) + np.arange(sizes.sum())]
            flats.append(other)
            counts.append(sizes)
        return np.concatenate(flats), np.concatenate(counts)

    def _keep(self, keys: np.ndarray, buf: np.ndarray, begin: np.ndarray, end: np.ndarray, flat: np.ndarray, sizes: np.ndarray) -> None:
        """New words go into the table when they are met anew, but for very long ones."""
        mark = (keys >> np.uint64(42)).astype(np.int64)
        place = (keys & np.uint64(PLACES - 1)).astype(np.int64)
        fits = (end - begin <= LONG_WORD) & (sizes < 256) & self.seen[mark] & (self.bytes[place] == 0)
        self.seen[mark] = True
        ends = np.cumsum(sizes)
        own, n, length = (ends - sizes)[fits], sizes[fits], (end - begin)[fits]
        if not len(n) or n.sum() > ROOM or length.sum() > ROOM:
            return
        if self.used + n.sum() > ROOM or self.byte_used + length.sum() > ROOM:
            self.renew()
        at, byte_at = self.used + np.cumsum(n) - n, self.byte_used + np.cumsum(length) - length
        self.ids[self.used : self.used + n.sum()] = flat[spread(own, n)]
        self.letters[self.byte_used : self.byte_used + length.sum()] = buf[spread(begin[fits], length)]
        self.used, self.byte_used = self.used + int(n.sum()), self.byte_used + int(length.sum())
        place = place[fits]
        for column, values in ((self.size, n), (self.bytes, length), (self.at, at), (self.byte_at, byte_at)):
            column[place] = values  # of two words with one place the last stays, in every column

    def parts(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The bytes, and the spans that are encoded by themselves: words, and a mark that ends one.

        If the tokenizer takes capitals as small letters, they become small here (but in words that may
        hold one of its special tokens).  If it parts letters, figures and marks, one mark after an ASCII
        letter or figure is a part of its own.  Either makes fewer parts to learn.
        """
        begin, end = word_spans(buf, off)
        if self.folds:
            low = LOWER[buf]
            for k in np.unique(np.searchsorted(begin, np.flatnonzero(buf == ord("<")), "right") - 1).tolist():
                low[begin[k] : end[k]] = buf[begin[k] : end[k]]
            buf = low
        if self.splits and len(begin):
            cut = (end - begin > 1) & MARK[buf[end - 1]] & ALNUM[buf[end - 2]]
            begin, end = np.sort(np.concatenate((begin, end[cut] - 1))), np.sort(np.concatenate((end, end[cut] - 1)))
        return buf, begin, end

    def encode(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the texts in buf, and one offset more than there are texts."""
        buf, begin, end = self.parts(buf, off)
        hashes, first = span_hashes(buf, begin, end), np.searchsorted(begin, off)
        keys, example, which = np.unique(hashes, return_index=True, return_inverse=True)
        alike = same_bytes(buf, begin, end - begin, buf, begin[example][which], (end - begin)[example][which])
        if not alike.all():  # other words with the hash of an example: each occurrence is a word of its own, and not kept
            odd = np.flatnonzero(~alike)
            which[odd] = len(keys) + np.arange(len(odd))
            example, keys = np.concatenate((example, odd)), np.concatenate((keys, hashes[odd]))
        begin, end = begin[example], end[example]
        place = (keys & np.uint64(PLACES - 1)).astype(np.int64)
        known = same_bytes(buf, begin, end - begin, self.letters, self.byte_at[place].astype(np.int64), self.bytes[place].astype(np.int64))
        old, new = np.flatnonzero(known), np.flatnonzero(~known)
        sizes, start = np.zeros(len(keys), dtype=np.int64), np.zeros(len(keys), dtype=np.int64)
        sizes[old], start[old] = self.size[place[old]], self.at[place[old]]
        pool = self.ids[spread(start[old], sizes[old])]
        start[old] = np.cumsum(sizes[old]) - sizes[old]
        if len(new):
            data = memoryview(buf)
            flat, n = self._learn([bytes(data[a:b]) for a, b in zip(begin[new].tolist(), end[new].tolist(), strict=True)])
            sizes[new], start[new] = n, len(pool) + np.cumsum(n) - n
            pool = np.concatenate((pool, flat))
            self._keep(keys[new], buf, begin[new], end[new], flat, n)
        ids = pool[spread(start[which], sizes[which])]
        return ids, np.concatenate(([0], np.cumsum(sizes[which])))[first]


PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"


def pieces(docs: DataFrame, path: str, length: int = LENGTH) -> DataFrame:
    """Rows (doc_id, start, length, ids_crc32, doc_tokens): every id, the end id included, lies in one piece."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = per_process(f"encoder {path}", lambda: Encoder(path))
        for batch in batches:
            for part in slices(batch, "text", ENCODE_BYTES):
                ids, at = encoder.encode(*utf8(part.column(1)))
                rows = []
                for doc, a, b in zip(part.column(0).to_pylist(), at[:-1].tolist(), at[1:].tolist(), strict=True):
                    own, n = ids[a:b].tobytes() + LAST, b - a + 1
                    rows += [(doc, s, min(length, n - s), zlib.crc32(own[4 * s : 4 * (s + length)]), n) for s in range(0, n, length)]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return map_arrow(docs.select("doc_id", "text"), work, PIECES)


def knapsack(values: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """Best multiset of sizes 1..len(values): its value and how many of each."""
    best, choice = np.zeros(capacity + 1), np.zeros(capacity + 1, dtype=np.int64)
    for c in range(1, capacity + 1):
        k = min(c, len(values))
        v = values[:k] + best[c - k : c][::-1]
        i = int(v.argmax())
        best[c], choice[c] = (v[i], i + 1) if v[i] > best[c - 1] else (best[c - 1], 0)
    out, c = np.zeros(len(values), dtype=np.int64), capacity
    while c > 0:
        if choice[c]:
            out[choice[c] - 1] += 1
            c -= choice[c]
        else:
            c -= 1
    return float(best[capacity]), out


def column_generation(demand: np.ndarray, gap: float = 5e-4, rounds: int = 3000) -> tuple[np.ndarray, np.ndarray]:
    """demand of sizes 1..m, stock of size m: patterns (columns) and their fractional numbers."""
    m = len(demand)
    sizes = np.flatnonzero(demand) + 1
    basis = np.zeros((m, len(sizes)))
    for k, s in enumerate(sizes):
        basis[s - 1, k] = m // s
    rows = sizes - 1
    inverse = np.diag(1.0 / (m // sizes))
    x = demand[rows] / (m // sizes)
    for _ in range(rounds):
        price = np.zeros(m)
        price[rows] = inverse.sum(axis=0)
        value, pattern = knapsack(price, m)
        if value <= 1 + gap:  # dividing the prices by value makes them feasible: the bound is x.sum() / value
            break
        u = (inverse * pattern[rows]).sum(axis=1)  # elementwise: threads of a linear algebra library would only contend here
        ok = u > 1e-9
        ratio = np.where(ok, x / np.where(ok, u, 1), np.inf)
        leave = int(ratio.argmin())
        t = ratio[leave]
        x = np.maximum(x - t * u, 0)
        x[leave] = t
        basis[:, leave] = pattern
        inverse[leave] /= u[leave]
        others = np.arange(len(sizes)) != leave
        inverse[others] -= np.outer(u[others], inverse[leave])
    return basis.astype(np.int64), x


def patterns(demand: np.ndarray) -> list[tuple[np.ndarray, int]]:
    """Whole patterns that meet the demand exactly: (number of each size, copies)."""
    m = len(demand)
    if not demand.sum():
        return []
    columns, x = column_generation(demand.astype(float))
    out, left = [], demand.astype(np.int64).copy()
    for column, n in zip(columns.T, np.floor(x + 1e-6).astype(np.int64), strict=True):
        used = column > 0
        n = int(min(n, (left[used] // column[used]).min())) if used.any() else 0
        if n > 0:
            out.append((column, n))
            left -= n * column
    while left.any():  # first-fit decreasing, pattern by pattern: as often as it goes
        room, fit = m, np.zeros(m, dtype=np.int64)
        for s in range(m, 0, -1):
            k = min(room // s, int(left[s - 1]))
            fit[s - 1], room = k, room - k * s
        used = fit > 0
        n = int((left[used] // fit[used]).min())
        out.append((fit, n))
        left -= n * fit
    return out


def plan(demand: np.ndarray) -> list[tuple[int, int, int, int, int]]:
    """Rows (class, first rank, rank after the last, first sequence, copies)."""
    out, given, sequence = [], np.zeros(len(demand), dtype=np.int64), 0
    for column, n in patterns(demand):
        for c in np.flatnonzero(column):
            to = given[c] + n * column[c]
            out.append((int(c) + 1, int(given[c]), int(to), sequence, n))
            given[c] = to
        sequence += n
    return out


def pack(docs: DataFrame, path: str | None = None, length: int = LENGTH, grain: int = GRAIN) -> DataFrame:
    spark = docs.sparkSession
    scratch = Scratch(spark, "packing")
    with small_batches(spark):
        cut = scratch.table(pieces(docs, path or tokenizer_path(), length), "pieces")
    cut = cut.withColumn("class", F.ceil(F.col("length") / grain).cast("int"))
    demand = np.zeros(length // grain, dtype=np.int64)
    for r in cut.groupBy("class").count().collect():  # length / grain rows at most
        demand[r["class"] - 1] = r["count"]
    table = local_rows(spark, plan(demand), "class int, lo bigint, hi bigint, first bigint, copies bigint")
    buckets = int(max(8, demand.sum() // RANK_ROWS))
    placed = ranked(cut, ["class"], [F.col("doc_id"), F.col("start")], buckets, F.xxhash64("doc_id", "start"), "rank")
    placed = placed.join(F.broadcast(table), "class").where("rank >= lo and rank < hi")  # a few rows a class: bounded by the classes
    placed = placed.withColumn("sequence_id", F.col("first") + (F.col("rank") - F.col("lo")) % F.col("copies")).withColumn("slot", F.expr("(rank - lo) div copies"))
    before = W.partitionBy("sequence_id").orderBy(F.desc("class"), "slot").rowsBetween(W.unboundedPreceding, -1)
    return placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long").alias("offset"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
