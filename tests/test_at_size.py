"""Work that grew faster than its input: copies of edges, frontiers, equal edges."""

from dataclasses import replace

import numpy as np

from motifspark import api, balance, kernels, measures
from motifspark.api import MineSpec, mine
from motifspark.catalog import MOTIFS, group
from motifspark.engines import brute, epochs
from motifspark.engines.levels import holding
from motifspark.graph import TemporalGraph
from motifspark.motif import Motif
from motifspark.tree import PrefixTree

EDGE = "edge_id bigint, src bigint, dst bigint, t bigint, tie bigint"


def graph(spark, rows):
    return TemporalGraph(spark.createDataFrame(rows, EDGE))


def drawn(n, vertices, span, seed=7):
    r = np.random.default_rng(seed)
    return [(k, int(a), int(b), int(t), k) for k, (a, b, t) in enumerate(zip(r.integers(0, vertices, n), r.integers(0, vertices, n), r.integers(0, span, n)))]


def test_epochs_copy_less_than_they_search(spark):
    """A slab of many edges and a budget of few candidates: as many owners as the budget asked for would get the whole slab each, epoch after epoch."""
    rows, delta = drawn(4_000, 300, 4_000), 400
    g, tree = graph(spark, rows), PrefixTree.build(group("C2"))
    a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
    want = kernels.tally(kernels.generic(tree), a, np.ones(len(rows), dtype=bool), delta)
    r = epochs.run(g.edges, tree, delta, balance.Slabs(delta, 10_000), budget=50, least_work=10)
    assert {x.motif: x.n for x in r.found.collect()} == {k: n for k, n in want.items() if n}
    assert sum(c[3] for c in r.costs) <= 4 and len(r.costs) <= 4


def test_last_edges_to_new_vertices_are_counted_by_rank():
    """Stars with many candidates a row: their last edges are not looked at, loops and bound vertices do not count."""
    rows = drawn(300, 4, 300, 3)
    a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
    motifs = [MOTIFS[m] for m in ("in_star3", "out_star3")]
    tree, every = PrefixTree.build(motifs), np.ones(len(rows), dtype=bool)
    want = {m.name: len(brute.matches(rows, m, 300)) for m in motifs}
    assert want["in_star3"] > 10_000
    looked = []
    a.candidates, inner = (lambda which, key, *x: looked.append(len(key)) or inner(which, key, *x)), a.candidates
    for make in (kernels.generic, kernels.specialised):
        looked.clear()
        assert kernels.tally(make(tree), a, every, 300) == {k: n for k, n in want.items() if n}
        assert len(looked) == 2, "only the steps before last edges are looked at"
    search = kernels.Search(a, tree, 300)
    total = {}
    for source in (search.start(every), search.run()):
        for q, _, n in source:
            total[q] = total.get(q, 0) + n
    assert total == {k: n for k, n in want.items() if n} and search.work < want["in_star3"] + want["out_star3"]


def test_large_frontiers_are_not_made(spark, monkeypatch):
    """Where frontiers are expected to be too large, levels and sql search slabs; equal edges, loops, predicates and anchors count as before."""
    rows = [(k, a, b, t // 40, k) for k, a, b, t, _ in drawn(500, 5, 800, 11)]  # days: many equal edges
    g = graph(spark, rows)
    motifs = [MOTIFS[m] for m in ("in_star3", "bifan", "tri_cycle", "path2")] + [Motif("odd", MOTIFS["path2"].edges, ("src % 2 = 1", None))]
    whole = MineSpec(g, motifs, 3, engine="levels")
    counts = lambda s: {r.motif: r.n for r in mine(s).collect()}
    want = counts(replace(whole, engine="fused"))
    anchored = counts(replace(whole, engine="fused", anchored="dst < 3"))
    listed = {tuple(r) for r in mine(replace(whole, motifs=motifs[2:4], engine="fused", mode="enumerate")).collect()}
    monkeypatch.setattr(api, "FRONTIER_ROWS", 100)
    monkeypatch.setattr(api, "Frontiers", None)
    monkeypatch.setattr(balance, "TASK_WORK", 2_000)
    assert counts(whole) == want and min(want.values()) > 0
    assert counts(replace(whole, engine="sql")) == want
    assert counts(replace(whole, anchored="dst < 3")) == anchored != want
    assert {tuple(r) for r in mine(replace(whole, motifs=motifs[2:4], mode="enumerate")).collect()} == listed


def test_ratios_of_groups_from_one_search(spark):
    """The same as each group by itself, with one persisted frame and no frontier."""
    g = graph(spark, drawn(400, 12, 900, 5))
    groups = {name: group(name) for name in ("D2", "F3", "C3")}
    with holding() as held:
        got = {r.group_name: (r.independent, r.shared) for r in measures.work_ratios(g, groups, 60).collect()}
    assert len(held) == 1
    for name, motifs in groups.items():
        r = measures.work_ratio(MineSpec(g, motifs, 60), name).first()
        assert got[name] == (r.independent, r.shared) and r.shared > 400


def test_budgets_grow_before_copies_outweigh_the_search(spark):
    """Eight edges for each candidate of the budget: owners by that budget would copy eight edges to look at one."""
    rows, delta = drawn(4_000, 300, 4_000), 400
    g, tree = graph(spark, rows), PrefixTree.build(group("D2"))
    a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
    want = kernels.tally(kernels.generic(tree), a, np.ones(len(rows), dtype=bool), delta)
    r = epochs.run(g.edges, tree, delta, balance.Slabs(delta, 10_000), budget=500, least_work=10, offload="one")
    assert {x.motif: x.n for x in r.found.collect()} == {k: n for k, n in want.items() if n}
    assert sum(c[3] for c in r.costs) <= 4 and len(r.costs) <= 4


def test_epochs_let_go_of_what_they_shuffled(spark, monkeypatch):
    """A hub and a small budget, many epochs: each lets its shuffle files go, and few are there at the end."""
    import time

    rows = [(k, k % 7 + 1, 0, k, k) for k in range(60)] + [(100 + k, 0, k % 7 + 1, 60 + k, 100 + k) for k in range(60)]
    tracked, called, let_go = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses, [], epochs.let_go
    before = tracked().size()
    monkeypatch.setattr(epochs, "let_go", lambda s: (called.append(s), let_go(s)))
    r = epochs.run(graph(spark, rows).edges, PrefixTree.build(group("C1")), 40, balance.Slabs(40, 1000), budget=100, least_work=0)
    assert len(r.costs) > 3 and len(called) == len(r.costs)
    for _ in range(20):
        let_go(spark)
        time.sleep(0.5)
        if tracked().size() <= before + 3:
            break
    assert tracked().size() <= before + 3


def test_places_known_from_edges_are_not_searched(monkeypatch):
    """Candidates whose key is an end of the first or the last edge, and pairs without a later edge, need no search; loops, parallel edges and equal times too."""
    rows = [(k, a, b, t // 3, k) for k, a, b, t, _ in drawn(900, 6, 900, 21)]
    tree = PrefixTree.build(list(MOTIFS.values()) + [Motif.parse("loop_out", "AA AB BC"), Motif.parse("in_loop", "AB BB BC")])
    for ties in ("strict", "sequence"):
        a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)), ties)
        search, composite, asked = kernels.Search(a, tree, 40), {k: v[0] for k, v in a.by.items()}, set()
        inner = search.spans

        def compared(p, q, which, key, first, last, a=a, inner=inner, composite=composite, asked=asked):
            lo, size = inner(p, q, which, key, first, last)
            want = np.searchsorted(composite[which], key * a.span + a.rank[last], "right")
            many = np.maximum(np.searchsorted(composite[which], key * a.span + a.last_rank(a.t[first] + 40), "right") - want, 0)
            assert (size == many).all() and (lo[size > 0] == want[size > 0]).all()
            asked.add((which, len(p)))
            return lo, size

        search.spans, total = compared, {}
        for source in (search.start(np.ones(len(rows), dtype=bool)), search.run()):
            for q, _, n in source:
                total[q] = total.get(q, 0) + n
        assert total == kernels.tally(kernels.generic(tree), a, np.ones(len(rows), dtype=bool), 40) and len(asked) > 6
    rows = drawn(3_000, 150, 3_000, 4)
    rows = [(k, 1_000 + a, b % 20, t, k) for k, a, b, t, _ in rows]  # senders receive nothing
    a, searched, plain = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5))), [], np.searchsorted
    search = kernels.Search(a, PrefixTree.build(group("C1")), 1_000)
    monkeypatch.setattr(np, "searchsorted", lambda x, v, *more: searched.append(np.size(v)) or plain(x, v, *more))
    for source in (search.start(np.ones(len(rows), dtype=bool)), search.run()):
        list(source)
    assert search.work > 100_000 and sum(searched) < 2 * search.work


def test_epochs_follow_equal_edges_once(spark):
    """Days as times and few vertices, each edge six times: counts as one by one, loops, predicates, anchors and replicas too, from a sixth of the roots."""
    rows = [(6 * k + c, a, b, t // 40, 6 * k + c) for k, a, b, t, _ in drawn(90, 5, 800, 11) for c in range(6)]
    g = graph(spark, rows)
    motifs = [MOTIFS[m] for m in ("path2", "lollipop", "tri_cycle", "out_star3")] + [Motif("odd", MOTIFS["path2"].edges, ("src % 2 = 1", None)), Motif.parse("loop_out", "AA AB BC")]
    tree = PrefixTree.build(motifs)
    a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)), passes={"src % 2 = 1": np.array([r[1] % 2 == 1 for r in rows])})
    tallied = lambda owned: kernels.tally(kernels.generic(tree), a, owned, 5)
    every, some = tallied(np.ones(len(rows), dtype=bool)), tallied(a.dst < 3)
    assert min(every.values()) > 0 and len(every) == len(motifs) and some != every
    r = epochs.run(g.edges, tree, 5, balance.Slabs(5, 100, (), 2), budget=150, least_work=400)
    assert {x.motif: x.n for x in r.found.collect()} == every and len(r.costs) > 1
    assert r.costs[0][1] <= 2 * 90 * len(tree.prefixes())
    r = epochs.run(g.edges, tree, 5, balance.Slabs(5, 10), anchored="dst < 3")
    assert {x.motif: x.n for x in r.found.collect()} == some


def test_only_owners_with_contexts_get_edges(spark, monkeypatch, tmp_path):
    """A task's contexts stay together: they have one owner, whatever the work would ask for; budgets double in the end, and no contexts are left behind."""
    from pyspark.sql.group import GroupedData

    rows = [(k, k % 7 + 1, 0, k, k) for k in range(200)] + [(300 + k, 0, k % 7 + 1, 200 + k, 300 + k) for k in range(200)]
    a, tree, copies = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5))), PrefixTree.build(group("D2")), []
    cogroup = GroupedData.cogroup
    monkeypatch.setattr(GroupedData, "cogroup", lambda self, other: (copies.append(other._df.count()), cogroup(self, other))[1])
    monkeypatch.setattr(epochs, "scratch_path", lambda s: f"file://{tmp_path}/epochs")
    r = epochs.run(graph(spark, rows).edges, tree, 150, balance.Slabs(150, 1000), budget=100, least_work=0, offload="one")
    want = kernels.tally(kernels.generic(tree), a, np.ones(len(rows), dtype=bool), 150)
    assert {x.motif: x.n for x in r.found.collect()} == {k: n for k, n in want.items() if n}
    assert r.costs[0][2] > 3_000 and 3 < len(r.costs) <= 12 and set(copies) == {len(rows)}
    assert all(p.name.endswith("-counts") for p in (tmp_path / "epochs").iterdir())


def test_weights_are_handed_over():
    """F3 on edges that are there five times, searched with weights by one search after another: counts as edge by edge."""
    rows = [(5 * k + c, a, b, t, 5 * k + c) for k, a, b, t, _ in drawn(120, 8, 120, 5) for c in range(5)]
    tree, columns = PrefixTree.build(group("F3")), [np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)]
    want = kernels.tally(kernels.generic(tree), kernels.Adjacency(*columns), np.ones(len(rows), dtype=bool), 30)
    merged = lambda: kernels.Adjacency(*(c[::5] for c in columns[:4]), np.zeros(120, dtype=np.int64), weight=np.full(120, 5))
    search, total, handed = kernels.Search(merged(), tree, 30), {}, 0
    begin = search.start(np.ones(120, dtype=bool))
    while True:
        for source in (begin, search.run(50)):
            for q, _, n in source:
                total[q] = total.get(q, 0) + n
        if not search.stack:
            break
        parts, search, begin, handed = list(search.left(10)), kernels.Search(merged(), tree, 30), iter(()), handed + 1
        for part in parts:
            search.resume(int(part["node"][0]), part)
    assert total == {k: n for k, n in want.items() if n} and set(total) == {m.name for m in group("F3")} and handed > 2
