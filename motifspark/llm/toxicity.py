"""Toxicity by multiple-instance learning.

A document is a bag of sentences.  Each sentence has a logistic score; the document's
score is their noisy-or (it is toxic if some sentence is).  Only documents are labelled:
the weights are fitted by gradient steps on the documents' likelihood, and the sentences'
scores that come out of it say where a document offends.

Features of a sentence are its lower-case words and the first four, five and six letters
of longer ones (inflected words share their stems).  Two passes over the labelled sample
are distributed: counting features by label, then encoding the sample with the features
chosen.  The fit itself runs on the driver on that encoded sample, whose rows are bounded
by MAX_TRAIN (chosen by a hash of doc_id) and whose columns by MAX_FEATURES.  Labels come
only from rows whose crc32(doc_id as text) mod 5 is not 0.

Defined results.  Null and empty texts are one empty sentence.  Rows that repeat get the
same score.  Documents without label are scored all the same.  If several labels exist for
a doc_id the highest counts; null labels count for nothing.  Without both classes in the
sample the base rate is the score.  An empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow_text import map_arrow, slices, small_batches
from .common import without

MAX_TRAIN, MAX_FEATURES, LEAST_DOCS, ROUNDS = 20_000, 4_000, 3, 300
SENTENCE = re.compile(r"[.!?\n]+")
WORD = re.compile(r"[^\W\d_]+")
STEMS = (4, 5, 6)


class Model(NamedTuple):
    weights: dict[str, float]
    bias: float


def sentences(text: str | None) -> list[str]:
    """Non-blank sentences; one empty one where there are none."""
    return [s for s in SENTENCE.split(text or "") if not s.isspace() and s] or [""]


def features(word: str) -> list[str]:
    return [word, *(f"{word[:k]}~" for k in STEMS if len(word) > k)]


def words(text: str) -> list[str]:
    return WORD.findall(text.lower())


def is_held_out(doc_id="doc_id"):
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def training_rows(labels: DataFrame, most: int = MAX_TRAIN) -> DataFrame:
    """(doc_id, y) of the bounded sample that may teach."""
    rows = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~is_held_out()).groupBy("doc_id").agg(F.max("toxic").alias("y"))
    return rows.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)


def counts(taught: DataFrame) -> DataFrame:
    """(feature, y, n): documents of each label that have the feature."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                out: dict[tuple[str, int], int] = {}
                for text, y in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    for f in {f for w in set(words(text or "")) for f in features(w)}:
                        out[f, y] = out.get((f, y), 0) + 1
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array([f for f, _ in out]), pa.array([y for _, y in out], pa.int32()), pa.array(list(out.values()), pa.int64())], ["feature", "y", "n"])

    return map_arrow(taught.select("text", "y"), work, "feature string, y int, n bigint").groupBy("feature").agg(F.sum(F.when(F.col("y") == 1, F.col("n")).otherwise(0)).alias("n1"), F.sum(F.when(F.col("y") == 1, 0).otherwise(F.col("n"))).alias("n0"))


def chosen(table: DataFrame, docs1: int, docs0: int) -> list[str]:
    """Features whose share among toxic documents is above that among the others, by z of the log odds."""
    a, b, c, d = F.col("n1") + 0.5, F.col("n0") + 0.5, docs1 - F.col("n1") + 0.5, docs0 - F.col("n0") + 0.5
    z = (F.log(a / c) - F.log(b / d)) / F.sqrt(1 / a + 1 / b + 1 / c + 1 / d)
    rows = table.where(F.col("n1") >= LEAST_DOCS).withColumn("z", z).where("z > 2.5").orderBy(F.desc("z"), "feature").limit(MAX_FEATURES)
    return [r["feature"] for r in rows.collect()]  # MAX_FEATURES rows at most


def encoded(taught: DataFrame, index: dict[str, int]) -> DataFrame:
    """(y, n, bags): n sentences, and the feature numbers of those that have any, -1 after each sentence."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                ys, ns, bags = [], [], []
                for text, y in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    bag, said = [], sentences(text)
                    for s in said:
                        if got := sorted({index[f] for w in words(s) for f in features(w) if f in index}):
                            bag += [*got, -1]
                    ys.append(y)
                    ns.append(len(said))
                    bags.append(bag)
                yield pa.RecordBatch.from_arrays([pa.array(ys, pa.int32()), pa.array(ns, pa.int64()), pa.array(bags, pa.list_(pa.int32()))], ["y", "n", "bags"])

    return map_arrow(taught.select("text", "y"), work, "y int, n bigint, bags array<int>")


def fit(rows: list[tuple[int, int, list[int]]], n_features: int, rounds: int = ROUNDS, penalty: float = 1e-3) -> tuple[np.ndarray, float]:
    """Weights and bias by Adam on the mean log likelihood of the noisy-or."""
    y = np.array([r[0] for r in rows], dtype=float)
    doc, sent, feat, empty, at = [], [], [], np.zeros(len(rows)), 0
    for d, (_, n, bag) in enumerate(rows):
        empty[d] = n - bag.count(-1)
        for f in bag:
            if f < 0:
                doc.append(d)
                at += 1
            else:
                sent.append(at)
                feat.append(f)
    doc, sent, feat = np.array(doc, dtype=np.int64), np.array(sent, dtype=np.int64), np.array(feat, dtype=np.int64)
    w, b = np.zeros(n_features), -4.0
    m, v = np.zeros(n_features + 1), np.zeros(n_features + 1)
    for step in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(b + np.bincount(sent, w[feat], at), -30, 30)))
        p0 = 1 / (1 + np.exp(-b))
        calm = np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-12)), len(rows)) + empty * np.log1p(-p0)
        whole = -np.expm1(calm)
        pull = np.where(y == 1, np.exp(calm) / np.maximum(whole, 1e-12), -1.0) / len(rows)  # d logL / d(-log(1-p)) per unit of p
        gs = pull[doc] * p
        g = np.append(np.bincount(feat, gs[sent], n_features) - penalty * w / max(1, n_features) ** 0.5, gs.sum() + (pull * empty).sum() * p0)
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        move = 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        w, b = np.maximum(w + move[:-1], 0.0), min(b + move[-1], -1.0)
    return w, float(b)


def train(docs: DataFrame, labels: DataFrame) -> Model:
    taught = docs.select("doc_id", "text").join(F.broadcast(training_rows(labels)), "doc_id").select("text", "y")
    n = {r["y"]: r["n"] for r in taught.groupBy("y").agg(F.count("*").alias("n")).collect()}
    pos, neg = n.get(1, 0), n.get(0, 0)
    if not pos or not neg:
        rate = min(max((pos + 0.5) / (pos + neg + 1), 1e-3), 1 - 1e-3)
        return Model({}, float(np.log(rate / (1 - rate))))
    names = chosen(counts(taught), pos, neg)
    index = {f: i for i, f in enumerate(names)}
    rows = sorted((r["y"], r["n"], r["bags"]) for r in encoded(taught, index).collect())  # MAX_TRAIN rows at most; sorted, so that the fit is the same each time
    w, b = fit(rows, len(names))
    return Model({f: float(w[i]) for f, i in index.items() if w[i] > 0}, b)


class Scorer:
    """Word weights are looked up once a word; the cache is bounded."""

    def __init__(self, model: Model, most: int = 200_000):
        self.model, self.cache, self.most = model, {}, most
        self.base = float(np.log1p(-1 / (1 + np.exp(-model.bias))))

    def weight(self, word: str) -> float:
        if len(self.cache) >= self.most:
            self.cache.clear()
        get = self.model.weights.get
        out = self.cache[word] = sum(get(f, 0.0) for f in features(word))
        return out

    def scores(self, text: str | None) -> list[tuple[int, float]]:
        """(sentence number, log of one minus its score), of the sentences that have any weight; and the rest's number."""
        cache, out, said = self.cache, [], sentences(text)
        for k, s in enumerate(said):
            found = words(s)
            z = sum(cache[w] if w in cache else self.weight(w) for w in set(found))
            if z > 0:
                out.append((k, -float(np.logaddexp(0.0, self.model.bias + z))))
        self.total = len(said)
        return out

    def document(self, text: str | None) -> tuple[float, int, list[int]]:
        got = self.scores(text)
        calm = sum(x for _, x in got) + self.base * (self.total - len(got))
        return float(-np.expm1(calm)), self.total, [k for k, x in got if -np.expm1(x) >= 0.5]


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, n_sentences, offending (numbers of the sentences that score 0.5 or more)."""
    shipped = docs.sparkSession.sparkContext.broadcast(tuple(model))  # MAX_FEATURES weights at most

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(Model(*shipped.value))
        for batch in batches:
            for part in slices(batch, "text"):
                rows = [scorer.document(t) for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([r[0] for r in rows], pa.float64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.list_(pa.int32()))], ["doc_id", "score", "n_sentences", "offending"])

    return map_arrow(docs.select("doc_id", "text"), work, "doc_id bigint, score double, n_sentences bigint, offending array<int>")


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    with small_batches(docs.sparkSession):
        model = train(docs, labels)
    out = score(docs, model)
    return out.select("doc_id", is_held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_sentences", "offending")


def survivors(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that are not rejected, with all their columns."""
    with small_batches(docs.sparkSession):
        model = train(docs, labels)
        return without(docs, lambda d: score(d, model).where("score >= 0.5"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic"))
