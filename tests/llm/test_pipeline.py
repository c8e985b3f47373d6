"""The corpus pipeline against a brute-force version of its stages."""

import re
from collections import defaultdict

import pytest

from motifspark.llm import toxicity

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def same(t):
    return re.sub(r"[\x20\x09-\x0d]+", " ", t or "")


def shingles(t):
    w = re.sub("[A-Z]", lambda m: m[0].lower(), t or "").encode().split()
    return {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def test_pipeline(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact dedup", "n-gram Jaccard join", "benchmark decontamination", "packing"]
    kept = {r.doc_id: r.text for r in docs.collect()}
    judged = toxicity.judge(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")).collect()  # the model itself is tested elsewhere
    for r in judged:
        if r.predicted:
            del kept[r.doc_id]
    first = {}
    for i in sorted(kept):
        first.setdefault(same(kept[i]), i)
    kept = {i: kept[i] for i in first.values()}
    sets = {i: shingles(t) for i, t in kept.items()}
    by = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            by[x].append(i)
    parent = {i: i for i in kept}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, s in sets.items():
        near = {j for x in s for j in by[x] if j > i}
        for j in near:
            if 100 * len(s & sets[j]) >= 75 * len(s | sets[j]):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    kept = {i: t for i, t in kept.items() if find(i) == i}
    norm = lambda t: re.findall(r"[^\W_]+", (t or "").lower())
    grams = lambda w, k: {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}
    items = [norm(r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    for w in items:
        if w:
            q = grams(w, min(5, len(w)))
            for i in [i for i, t in kept.items() if 100 * len(q & grams(norm(t), min(5, len(w)))) >= 75 * len(q)]:
                del kept[i]
    out = corpus_pipeline.run(spark, sf_dir).collect()
    assert {r.doc_id for r in out} == set(kept)
    for i in kept:
        assert sum(r.length for r in out if r.doc_id == i) == next(r.doc_tokens for r in out if r.doc_id == i)


def test_every_stage_takes_an_empty_table(spark, sf_dir):
    empty = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, sf_dir).count() == 0
