"""Language of web pages by Bayesian fusion of four kinds of evidence.

posterior(l) ~ prior(l | host) * P(text | l) * P(declared markup language | l) * P(address suffix | l)

* Text: naive Bayes over hashed byte trigrams of the visible text, trained on a bounded
  sample of each language's labelled documents (DOCS_A_LANGUAGE, by a hash of doc_id), so
  that every language found can be given.  Trigrams depend on each other, so a text counts
  as at most EFFECTIVE independent ones.
* Declared language (``<html lang>``) and address suffix (the host's last label): counts
  over all pages of value by text language, smoothed.
* Host prior: counts by text language of the host, smoothed towards those of its parent
  domain, those towards all pages' (grouped aggregates, map-side combined).

Defined results.  Null urls have the empty host and suffix, null html is an empty text;
missing evidence is a value of its own ("").  Repeated rows get the same result and count
as often as they stand there.  Without labelled documents the language is null.  Empty
tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .arrow_text import map_arrow, slices, small_batches
from .common import Scratch, joined_hot, small

DOCS_A_LANGUAGE, BUCKETS, EFFECTIVE, STRENGTH = 1_000, 1 << 15, 60, 5.0
OPENING, HTML = re.compile(r"<(script|style|head)\b", re.IGNORECASE), re.compile(r"<html\b", re.IGNORECASE)
CLOSING = {t: re.compile(rf"</{t}\s*>", re.IGNORECASE) for t in ("script", "style", "head")}
LANG = re.compile(r"\blang\s*=\s*[\"']?([A-Za-z]+)", re.IGNORECASE)


def visible(markup: str | None) -> str:
    """The text outside tags, comments, scripts, styles and the head, entities resolved.

    One pass: of each kind of end the next place is remembered, so that openings that nothing closes
    (they are taken as plain tags, or as text without a ``>``) are not searched for again and again.
    """
    text, out, at = markup or "", [], 0
    ends: dict[str, tuple[int, int]] = {}

    def end_of(kind: str, after: int) -> int:
        """Place behind the next end of the kind from there on; -1 if there is none."""
        where, behind = ends.get(kind, (-2, -2))
        if where == -1 or where >= after:
            return behind
        if kind in CLOSING:
            m = CLOSING[kind].search(text, after)
            ends[kind] = (m.start(), m.end()) if m else (-1, -1)
        else:
            k = text.find(kind, after)
            ends[kind] = (k, k + len(kind)) if k >= 0 else (-1, -1)
        return ends[kind][1]

    while (open_ := text.find("<", at)) >= 0:
        out.append(text[at:open_])
        stop = end_of("-->", open_ + 4) if text.startswith("<!--", open_) else -1
        if stop < 0 and (m := OPENING.match(text, open_)):
            stop = end_of(m[1].lower(), m.end())
        if stop < 0:
            stop = end_of(">", open_ + 1)
        if stop < 0:
            at = open_
            break
        out.append(" ")
        at = stop
    return entities.unescape("".join(out) + text[at:])


def declared_in(markup: str | None) -> str:
    """The language that an ``<html`` tag declares, in lower case; "" if none does."""
    text, at = markup or "", 0
    while m := HTML.search(text, at):
        end = text.find(">", m.end())
        end = len(text) if end < 0 else end
        if found := LANG.search(text, m.end(), end):
            return found[1].lower()
        at = end
    return ""


def trigrams(text: str) -> np.ndarray:
    """Buckets of the byte trigrams of the text, in lower case, white space as one blank."""
    b = np.frombuffer(f" {' '.join(text.lower().split())} ".encode(), dtype=np.uint8).astype(np.uint32)
    if len(b) < 3:
        return np.zeros(0, dtype=np.int64)
    code = (b[:-2] << 16) | (b[1:-1] << 8) | b[2:]
    return ((code * np.uint32(2654435761)) >> np.uint32(17)).astype(np.int64)


def train(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """Languages, all there are, and their log probabilities of the buckets."""
    place = F.row_number().over(W.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id"))
    ids = docs.where("lang is not null and doc_id is not null").select("lang", "doc_id").distinct().withColumn("place", place).where(F.col("place") <= DOCS_A_LANGUAGE).drop("place")
    ids = Scratch(docs.sparkSession, "language").table(ids, "sample")
    taught = docs.select("doc_id", "lang", "text").where("lang is not null").join(small(ids), ["lang", "doc_id"]).select("lang", "text")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total: dict[str, np.ndarray] = {}
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                total[lang] = total.get(lang, 0) + np.bincount(trigrams(text or ""), minlength=BUCKETS)
            for lang, n in total.items():
                at = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(n[at])], ["lang", "bucket", "n"])

    rows = map_arrow(taught, work, "lang string, bucket int, n bigint").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    got = {}
    for r in rows.groupBy("lang").agg(F.collect_list("bucket").alias("at"), F.collect_list("n").alias("n")).toLocalIterator():  # a row a language, BUCKETS numbers at most
        n = np.full(BUCKETS, 0.5)
        n[r["at"]] += r["n"]
        got[r["lang"]] = np.log(n / n.sum())
    langs = sorted(got)
    return langs, np.array([got[x] for x in langs])


def evidence(pages: DataFrame, langs: list[str], table: np.ndarray) -> DataFrame:
    """(page_id, host, parent, suffix, declared, ll, best): the text's log likelihoods, one a language."""
    shipped = pages.sparkSession.sparkContext.broadcast(table)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        logs = shipped.value
        for batch in batches:
            for part in slices(batch, "html"):
                hosts, parents, suffixes, said, lls, best = [], [], [], [], [], []
                for url, markup in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True):
                    host = re.split(r"[/?#]", (url or "").partition("://")[2], maxsplit=1)[0].lower()
                    labels = host.split(".")
                    at = trigrams(visible(markup))
                    ll = logs[:, at].sum(axis=1) * min(1.0, EFFECTIVE / max(1, len(at)))
                    hosts.append(host)
                    parents.append(".".join(labels[-2:]))
                    suffixes.append(labels[-1])
                    said.append(declared_in(markup))
                    lls.append((ll - ll.max()).tolist())
                    best.append(int(ll.argmax()))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, pa.string()) for c in (hosts, parents, suffixes, said)), pa.array(lls, pa.list_(pa.float64())), pa.array(best, pa.int32())], ["page_id", "host", "parent", "suffix", "declared", "ll", "best"])

    return map_arrow(pages.select("page_id", "url", "html"), work, "page_id bigint, host string, parent string, suffix string, declared string, ll array<double>, best int")


def tally(rows: DataFrame, by: list[str], n: int, out: str) -> DataFrame:
    """Counts by text language, as an array."""
    return rows.groupBy(*by).agg(F.array(*(F.sum(F.when(F.col("best") == i, 1.0).otherwise(0.0)) for i in range(n))).alias(out))


def shares(counts: Column, towards: Column) -> Column:
    total = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)
    return F.zip_with(counts, towards, lambda c, p: (c + STRENGTH * p) / (total + STRENGTH))


def likelihoods(rows: DataFrame, by: str, whole: list[float], n: int) -> DataFrame:
    """(value, log P(value | l)), additively smoothed over the values seen and one more."""
    counts = tally(rows, [by], n, "c")
    values = counts.count() + 1
    return counts.select(by, F.transform(F.zip_with("c", F.array(*map(F.lit, whole)), lambda c, t: (c + 0.5) / (t + 0.5 * values)), lambda x: F.log(x)).alias(f"l_{by}"))


def identify(pages: DataFrame, docs: DataFrame) -> DataFrame:
    """page_id, lang, confidence, text_lang, declared, host."""
    spark = pages.sparkSession
    langs, table = train(docs)
    if not langs:
        return pages.select("page_id", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("confidence"), F.lit(None).cast("string").alias("text_lang"), F.lit(None).cast("string").alias("declared"), F.lit(None).cast("string").alias("host"))
    n = len(langs)
    with small_batches(spark):
        rows = Scratch(spark, "language").table(evidence(pages, langs, table), "evidence")
    whole = tally(rows, [], n, "c").collect()[0]["c"]  # one row
    whole = [x or 0.0 for x in whole]
    everywhere = F.array(*(F.lit((x + 1) / (sum(whole) + n)) for x in whole))
    parents = tally(rows, ["parent"], n, "pc").select("parent", shares(F.col("pc"), everywhere).alias("pp"))
    hosts = tally(rows, ["host", "parent"], n, "hc").join(parents, "parent").select("host", F.transform(shares(F.col("hc"), F.col("pp")), lambda x: F.log(x)).alias("l_host"))
    fused = joined_hot(rows, Scratch(spark, "language").table(hosts, "hosts"), "host")  # a host may hold a third of all pages
    for by in ("declared", "suffix"):
        fused = fused.join(small(likelihoods(rows, by, whole, n)), by)
    total = F.col("ll")
    for c in ("l_host", "l_declared", "l_suffix"):
        total = F.zip_with(total, c, lambda a, b: a + b)
    fused = fused.withColumn("total", total).withColumn("top", F.array_max("total"))
    names = F.array(*map(F.lit, langs))
    norm = F.aggregate("total", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top")))
    return fused.select("page_id", F.get(names, F.array_position("total", F.col("top")).cast("int") - 1).alias("lang"), F.round(1 / norm, 6).alias("confidence"), F.get(names, F.col("best")).alias("text_lang"), "declared", "host")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/pages.parquet"), spark.read.parquet(f"{sf_dir}/documents.parquet"))
