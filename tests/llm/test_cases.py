"""Odd rows for every operator: clashing columns, repeated ids, very long texts; and plain recounts of the learned ones."""

import math
import random
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifspark.llm import decontaminate, exact_dedup, jaccard_join, language_id, packing, repeated_passages, secret_scan, sharding, toxicity, url_rules
from motifspark.llm.common import joined_hot, local_rows, scratch_scope, shared_dir

CLASH = ["_row", "_key", "_p", "key", "row", "rank", "p", "slot_", "n", "gone", "id", "of", "digest", "file", "passages", "items", "rid", "fp", "w", "c"]


def wording(rng, n, vocabulary=4000):
    return " ".join(f"w{rng.randrange(vocabulary)}" for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Copies, near copies, a repeated id with another text, null ids and texts, and columns named as ours are."""
    rng = random.Random(2)
    a, b, c, passage = wording(rng, 80), wording(rng, 80), wording(rng, 80), wording(rng, 60)
    rows = [(1, a), (2, a), (2, b), (3, f"{a} end"), (None, a), (None, None), (4, ""), (5, f"{b} {passage} x"), (6, f"{passage} y"), (7, c), (7, c), (8, f"vile {c}")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(2)
    for name in CLASH:
        df = df.withColumn(name, F.lit(f"mine {name}"))
    return df


def untouched(df, columns):
    assert df.columns == columns
    rows = df.collect()
    assert all(r[name] == f"mine {name}" for r in rows for name in CLASH)
    return sorted(((r.doc_id, r.text) for r in rows), key=str)


def test_clashing_columns(spark, odd):
    """Columns that the operators use inside too come through as they were, whole rows are kept or dropped."""
    cols = odd.columns
    texts = odd.select("doc_id", "text").collect()
    assert len(untouched(exact_dedup.survivors(odd), cols)) == len({r.text or "" for r in texts})
    near = untouched(jaccard_join.survivors(odd), cols)
    assert len([t for _, t in near if t and t.startswith(texts[0].text[:20])]) <= len(near)
    bench = spark.createDataFrame([(1, next(r.text for r in texts if r.doc_id == 7))], "item_id bigint, text string")
    assert {i for i, _ in untouched(decontaminate.survivors(odd, bench), cols)} == {1, 2, 3, None, 4, 5, 6}
    labels = spark.createDataFrame([(k, int(k == 8)) for k in range(9)], "doc_id bigint, toxic int")
    assert len(untouched(toxicity.survivors(odd, labels), cols)) <= len(texts)
    shards = sharding.shard(odd, 3, [F.col("doc_id"), F.xxhash64("text")])
    assert len(untouched(shards.drop("shard", "slot"), cols)) == len(texts)
    found = repeated_passages.passages(odd)
    assert {r.doc_id for r in found.collect()} >= {5, 6}
    cut = repeated_passages.without(odd, found)
    assert len(untouched(cut, cols)) == len(texts)
    assert packing.pack(odd).agg(F.countDistinct("doc_id")).first()[0] == 8
    assert secret_scan.scan(odd).count() == len(texts)
    assert exact_dedup.classes(odd).count() == jaccard_join.classes(odd).count() == toxicity.judge(odd, labels).count() == len(texts)


def test_an_id_that_repeats_is_judged_text_by_text(spark):
    rows = [(1, "fine words here"), (1, "vile"), (2, "fine words here too")]
    lab = spark.createDataFrame([(100 + k, k % 2) for k in range(80)], "doc_id bigint, toxic int")
    rows += [(100 + k, f"w{k} {'vile' if k % 2 else 'mild'}") for k in range(80)]
    kept = {(r.doc_id, r.text) for r in toxicity.survivors(spark.createDataFrame(rows, "doc_id bigint, text string"), lab).where("doc_id < 100").collect()}
    assert kept == {(1, "fine words here"), (2, "fine words here too")}


def test_very_long_texts(spark):
    """Texts of a megabyte in every operator."""
    rng = random.Random(4)
    long = wording(rng, 150_000, 50_000)
    rows = [(0, long), (1, f"{long} end"), (2, "x" * 1_000_000), (3, "short one"), (4, "a." * 300_000)]
    d = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert {r.doc_id: r.component_id for r in jaccard_join.classes(d).collect()} == {0: 0, 1: 0, 2: 2, 3: 3, 4: 4}
    assert {r.doc_id: r.n_words for r in repeated_passages.passages(d).collect()} == {0: 150_000, 1: 150_000}
    lab = spark.createDataFrame([(k, k % 2) for k in range(5)], "doc_id bigint, toxic int")
    assert toxicity.judge(d, lab).where("score between 0 and 1").count() == 5
    assert secret_scan.scan(d).count() == exact_dedup.classes(d).count() == 5
    pages = d.select(F.col("doc_id").alias("page_id"), F.concat(F.lit("http://a.test/"), "text").alias("url"), F.col("text").alias("html"))
    docs = spark.createDataFrame([(k, "one two three" if k % 2 else "un deux trois", "en" if k % 2 else "fr") for k in range(20)], "doc_id bigint, text string, lang string")
    assert language_id.identify(pages, docs).count() == 5
    assert url_rules.judge(pages, lab.withColumn("quality", F.lit(1))).where("verdict = 'allow'").count() == 5
    bench = spark.createDataFrame([(1, long[5000:9000].split(" ", 1)[1].rsplit(" ", 1)[0])], "item_id bigint, text string")
    assert {r.doc_id for r in decontaminate.matches(d, bench).collect()} == {0, 1}


def seconds(f, *args):
    t = time.perf_counter()
    f(*args)
    return time.perf_counter() - t


def test_rules_take_time_in_proportion():
    """What made rules look at a byte over and over: long schemes, unended tokens, unclosed markup."""
    scanner = secret_scan.Scanner(secret_scan.BASE + secret_scan.MORE)
    for text in ("http://x " + "a" * 400_000, "eyJ" * 150_000, "password " * 40_000, "-----BEGIN " + "A " * 200_000, "bearer " + " " * 400_000):
        buf = np.frombuffer(text.encode(), dtype=np.uint8)
        assert seconds(scanner.scan, buf, np.array([0, len(buf)])) < 5
    for text in ("<script" * 60_000, "<!-- " * 80_000, "<html " * 60_000, "<" * 400_000, "<style>" * 50_000 + "</script>"):
        assert seconds(language_id.visible, text) < 5
        assert seconds(language_id.declared_in, text) < 5


def test_visible_text_equals_the_plain_expression():
    gone = re.compile(r"<!--.*?-->|<(script|style|head)\b.*?</\1\s*>|<[^>]*>", re.DOTALL | re.IGNORECASE)
    declared = re.compile(r"<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z]+)", re.IGNORECASE)
    rng = random.Random(0)
    parts = ["<!--", "-->", "<script", "</script >", "<Style>", "</style>", "<head>", "</head>", "<p>", ">", "<", " x ", "word", "<html", " lang=", '"fr"', "lang = en", "<header>", "</HEAD>", "-", "<!", "--"]
    for _ in range(3000):
        text = "".join(rng.choice(parts) for _ in range(rng.randrange(14)))
        assert language_id.visible(text) == gone.sub(" ", text), text
        m = declared.search(text)
        assert language_id.declared_in(text) == (m[1].lower() if m else ""), text


def test_shard_query_contract(spark, sf_dir):
    """Every column of the query recomputed from the documents."""
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    out = sharding.query(spark, sf_dir).collect()
    assert sorted(r.doc_id for r in out) == sorted(docs)
    slots = defaultdict(list)
    for r in out:
        data = (docs[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32, r.law, r.grown_shard) == (len(data) + 8, zlib.crc32(data), "rows", None)
        slots[r.shard].append(r.slot)
    assert set(slots) == set(range(24)) and all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert max(map(len, slots.values())) - min(map(len, slots.values())) <= 1


def test_sharding_needs_no_python_worker(spark, odd):
    plan = sharding.shard(odd, 3, [F.col("doc_id")])._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "ExistingRDD" not in plan.replace("Scan ExistingRDD[doc_id", "")


def test_toxic_scores_by_hand(spark):
    """The scores recomputed sentence by sentence from the weights, and the fit's likelihood from a plain sum."""
    rng = random.Random(8)
    rows = [(k, ". ".join(f"{wording(rng, 5, 200)}{' vile' if k % 3 == 0 and j == 1 else ''}" for j in range(3))) for k in range(300)]
    d = spark.createDataFrame(rows, "doc_id bigint, text string")
    lab = spark.createDataFrame([(k, int(k % 3 == 0)) for k in range(300)], "doc_id bigint, toxic int")
    model = toxicity.train(d, lab)
    sigmoid = lambda z: 1 / (1 + math.exp(-z))

    def by_hand(text):
        calm = 1.0
        for s in re.split(r"[.!?\n]+", text):
            words = set(re.findall(r"[^\W\d_]+", s.lower()))
            z = sum(model.weights.get(f, 0.0) for w in words for f in [w, *(w[:k] + "~" for k in (4, 5, 6) if len(w) > k)])
            calm *= 1 - sigmoid(model.bias + z)
        return 1 - calm

    got = {r.doc_id: r.score for r in toxicity.score(d, model).collect()}
    assert all(abs(got[i] - by_hand(t)) < 1e-9 for i, t in rows)
    assert all((got[i] >= 0.5) == (i % 3 == 0) for i, _ in rows if zlib.crc32(str(i).encode()) % 5 == 0)

    bags = [(int(k % 2), 3, [0, -1, 1, -1] if k % 2 else [1, -1]) for k in range(40)]

    def likelihood(w, b):
        out = 0.0
        for y, n, bag in bags:
            parts = [p.split() for p in " ".join(map(str, bag)).split("-1")][:-1]
            calm = math.prod(1 - sigmoid(b + sum(w[int(f)] for f in p)) for p in parts) * (1 - sigmoid(b)) ** (n - len(parts))
            out += math.log(1 - calm if y else calm)
        return out

    start, middle, end = (likelihood(*toxicity.fit(bags, 2, rounds=k)) for k in (1, 30, 300))
    assert start < middle < end


def test_language_evidence_is_fused_as_written(spark):
    """Posterior of every page recomputed from its text's likelihoods and plain counts."""
    rng = random.Random(6)
    say = {"en": "the of and to in is that it was for", "fr": "le la et les des en un une du que", "de": "der die und das ist nicht ein zu mit"}
    docs = [(k, " ".join(rng.choices(say[lang].split(), k=40)), lang) for k, lang in enumerate(list(say) * 20)]
    pages = []
    for k in range(120):
        lang = rng.choice(list(say))
        host = f"{rng.choice('abc')}.{lang if rng.random() < 0.8 else 'en'}site.{rng.choice(['com', 'fr', 'de'])}"
        pages.append((k, f"http://{host}/x" if k % 17 else None, f"<html lang='{lang if rng.random() < 0.7 else 'en'}'><p>{' '.join(rng.choices(say[lang].split(), k=rng.randrange(0, 12)))}</p></html>" if k % 13 else None))
    d, p = spark.createDataFrame(docs, "doc_id bigint, text string, lang string"), spark.createDataFrame(pages, "page_id bigint, url string, html string")
    langs, table = language_id.train(d)
    rows = {r.page_id: r for r in language_id.evidence(p, langs, table).collect()}
    n, strength = len(langs), language_id.STRENGTH
    whole = Counter(r.best for r in rows.values())
    every = [(whole[i] + 1) / (len(rows) + n) for i in range(n)]

    def shares(same, towards):
        c = Counter(r.best for r in same)
        return [(c[i] + strength * towards[i]) / (len(same) + strength) for i in range(n)]

    def likelihood(by, value):
        values = len({r[by] for r in rows.values()}) + 1
        c = Counter(r.best for r in rows.values() if r[by] == value)
        return [(c[i] + 0.5) / (whole[i] + 0.5 * values) for i in range(n)]

    for r in language_id.identify(p, d).collect():
        e = rows[r.page_id]
        prior = shares([x for x in rows.values() if x.host == e.host], shares([x for x in rows.values() if x.parent == e.parent], every))
        said, suffix = likelihood("declared", e.declared), likelihood("suffix", e.suffix)
        score = [e.ll[i] + math.log(prior[i]) + math.log(said[i]) + math.log(suffix[i]) for i in range(n)]
        best = max(range(n), key=score.__getitem__)
        assert r.lang == langs[best] and abs(r.confidence - 1 / sum(math.exp(x - score[best]) for x in score)) < 2e-6


def test_url_verdicts_from_counted_rules(spark, sf_dir):
    """Mined verdicts on the given tables, from supports and confidences counted here."""
    pages, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("pages", "labels"))
    bad = {r.doc_id: r.quality == 0 or r.toxic == 1 for r in labels.collect()}

    def tokens(url):
        rest = (url or "").partition("://")[2]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        parts = [x for x in host.lower().split(".") if x]
        query = re.search(r"\?([^#]*)", url or "")
        out = {"h=" + ".".join(parts[k:]) for k in range(len(parts))} | {"p=" + s for s in path.split("/") if s and not re.search("[0-9]", s)}
        return (out | {"q=" + x.split("=")[0] for x in (query[1] if query else "").split("&") if x}) if host else set()

    items = {r.page_id: tokens(r.url) for r in pages.collect()}
    some, ill = Counter(), Counter()
    from itertools import combinations

    for i, t in items.items():
        if i in bad and t:
            for k in range(1, len(t) + 1):
                for c in combinations(sorted(t), k):
                    some[c] += 1
                    ill[c] += bad[i]
    rules = [set(c) for c in some if ill[c] >= url_rules.MIN_BAD and ill[c] / some[c] >= url_rules.MIN_CONFIDENCE]
    got = {r.page_id: r for r in url_rules.query(spark, sf_dir).collect()}
    assert set(got) == set(items)
    for i, t in items.items():
        mined = any(r <= t for r in rules)
        assert got[i].mined == mined
        if got[i].rule is None:
            assert got[i].verdict == ("block" if mined else "allow")


def test_local_rows_and_hot_joins(spark, monkeypatch):
    got = local_rows(spark, [(1, "a\n'b\"", None), (2, None, [1, 2**60])], "k int, s string, x array<bigint>")
    assert sorted(map(tuple, got.collect())) == [(1, "a\n'b\"", None), (2, None, [1, 2**60])]
    assert local_rows(spark, [], "k int").count() == 0
    rows = spark.range(1000).select("id", F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id")).alias("k"))
    unique = spark.range(500).select(F.col("id").alias("k"), (F.col("id") * 2).alias("v"))
    want = sorted((r.id, r.k, r.v) for r in rows.join(unique, "k", "left").collect())
    monkeypatch.setattr("motifspark.llm.common.BROADCAST_ROWS", 10)
    assert sorted(((r.id, r.k, r.v) for r in joined_hot(rows, unique, "k", "left").collect()), key=str) == sorted(want, key=str)


def test_scratch_is_in_the_shared_folder_and_goes(spark, tmp_path, monkeypatch):
    docs = spark.createDataFrame([(k, f"text {k % 5}") for k in range(20)], "doc_id bigint, text string")
    with monkeypatch.context() as m:
        m.setattr("motifspark.llm.common.shared_dir", lambda s: f"file://{tmp_path}")
        with scratch_scope(spark):
            assert exact_dedup.survivors(docs).count() == 5 and any(tmp_path.iterdir())
        assert not [p for p in tmp_path.iterdir() if p.is_dir()]

    class Cluster:
        class sparkContext:  # noqa: N801
            master = "spark://somewhere"

            @staticmethod
            def getConf():
                return {}

        conf: dict = {}

    with pytest.raises(ValueError, match="checkpoint.dir"):
        shared_dir(Cluster())


def test_session_is_left_as_it_was(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    d = spark.createDataFrame([(1, "a b c d e f")], "doc_id bigint, text string")
    packing.pack(d).collect()
    jaccard_join.classes(d).collect()
    assert spark.conf.get(name) == before
