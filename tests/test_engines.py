"""All engines against brute force: hand fixtures, random graphs, invariants."""

import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifspark import balance, baselines, kernels, measures
from motifspark.api import MineSpec, mine, window
from motifspark.catalog import GROUPS, MOTIFS, group
from motifspark.engines import brute, epochs
from motifspark.engines.levels import Frontiers, Fused, release
from motifspark.graph import DAY, EDGES, TemporalGraph, from_tables
from motifspark.motif import Motif
from motifspark.sources import readers
from motifspark.tree import PrefixTree

LOOPS = [Motif.parse("l1", "AA"), Motif.parse("l2", "AA AB"), Motif.parse("l3", "AB BB"), Motif.parse("l4", "AB BB BA"), Motif.parse("l5", "AA AB BB BA")]
#: edges, then (window, ties, counts that are not zero)
FIXTURES = {
    "F0": ("1>2@10 2>3@11 3>1@12 1>2@13 4>1@20 2>4@30 2>3@50", [(30, "strict", {"path2": 5, "path3": 1, "tri_cycle": 2, "burst2": 1}), (37, "strict", {"path2": 6, "path3": 1, "tri_cycle": 2, "burst2": 1}), (38, "strict", {"path2": 6, "path3": 1, "tri_cycle": 3, "burst2": 1})]),
    "F1": ("1>2@10 2>3@10 3>1@10 1>2@20 2>3@20", [(10, "strict", {"path2": 2, "burst2": 2}), (10, "sequence", {"path2": 5, "tri_cycle": 3, "burst2": 2})]),
    "F2": ("1>2@1 1>2@2 2>3@3 2>3@4 3>1@5 3>1@6", [(10, "strict", {"path2": 8, "tri_cycle": 8, "burst2": 3}), (3, "strict", {"path2": 8, "tri_cycle": 2, "burst2": 3})]),
    "F3": ("1>1@1 1>2@2 2>2@3 2>1@4 1>1@5 1>2@6", [(10, "strict", {"pingpong2": 2, "pingpong3": 1, "burst2": 1, "l1": 3, "l2": 4, "l3": 2, "l4": 2, "l5": 2})]),
    "F4": ("1>-1@1 -1>2@2 2>-2@3 -2>1@4 1>-1@5 -1>1@6 2>-1@7 2>-2@8", [(10, "strict", {"path2": 5, "path3": 4, "quad_cycle": 2, "pingpong2": 3, "burst2": 2})]),
    "F5": ("1>2@1", [(10, "strict", {})]),
    "F6": ("1>2@1 2>3@2 3>4@3 4>2@4 2>1@5 4>1@6 3>1@7", [(10, "strict", {"path2": 6, "path3": 3, "tri_cycle": 2, "tri_ff": 2, "lollipop": 1, "quad_cycle": 1, "lollipop_ret": 1, "pingpong2": 1, "in_star3": 1})]),
    "F8": ("0>1@1 0>2@2 0>3@3 0>4@4 0>5@5 1>0@6 2>0@7 3>0@8 4>0@9 5>0@10", [(20, "strict", {"pingpong2": 5, "out_star3": 10, "in_star3": 10})]),
    "F9": ("1>2@8 2>3@9 3>1@10 3>4@11 4>1@12 1>3@18 2>3@19 3>2@20", [(5, "strict", {"path2": 5, "path3": 2, "tri_cycle": 1, "quad_cycle": 1, "pingpong2": 1}), (10, "strict", {"path2": 6, "path3": 3, "tri_cycle": 2, "tri_ff": 1, "lollipop": 1, "quad_cycle": 1, "pingpong2": 2, "burst2": 1, "out_star3": 1})]),
}


def read(text):
    out = []
    for k, part in enumerate(text.split()):
        ends, t = part.split("@")
        a, b = ends.split(">")
        out.append((k, int(a), int(b), int(t), k))
    return out


def graph(spark, rows):
    return TemporalGraph(spark.createDataFrame(rows, EDGES))


def kernel_counts(rows, motifs, delta, ties="strict", make=kernels.specialised):
    """The kernels without Spark."""
    t = PrefixTree.build(motifs)
    if not rows:
        return dict.fromkeys(t.queries, 0)
    rows = sorted(rows, key=lambda r: (r[3], r[4]))
    a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)), ties)
    got = kernels.tally(make(t), a, np.ones(len(rows), dtype=bool), delta)
    return {q: got.get(t.aliases.get(q, q), 0) for q in t.queries}


def counts(df):
    return {r.motif: r.n for r in df.collect()}


@pytest.mark.parametrize("name", FIXTURES)
def test_fixtures(name):
    text, cases = FIXTURES[name]
    rows, motifs = read(text), [*MOTIFS.values(), *LOOPS]
    for delta, ties, want in cases:
        expected = {m.name: want.get(m.name, 0) for m in motifs}
        assert {m.name: len(brute.matches(rows, m, delta, ties)) for m in motifs if len(rows) < 9 or len(m) < 5} == {k: v for k, v in expected.items() if len(rows) < 9 or len(MOTIFS.get(k, [0])) < 5}
        if name == "F3":
            assert kernel_counts(rows, motifs, delta, ties) == expected
        else:
            assert {k: v for k, v in kernel_counts(rows, motifs, delta, ties).items() if k in MOTIFS} == {k: v for k, v in expected.items() if k in MOTIFS}


@pytest.mark.parametrize("seed", range(12))
def test_random_graphs_in_kernels(seed):
    rng = random.Random(seed)
    rows = [(k, rng.randrange(6), rng.randrange(6), rng.randrange(20), k) for k in range(rng.randrange(0, 24))]
    motifs = rng.sample([*MOTIFS.values(), *LOOPS, Motif.parse("apart", "AB CD"), Motif.parse("free_loop", "AB CC")], 9)
    delta = rng.randrange(1, 12)
    for ties in ("strict", "sequence"):
        want = {m.name: len(brute.matches(rows, m, delta, ties)) for m in motifs}
        assert kernel_counts(rows, motifs, delta, ties) == want
        assert kernel_counts(rows, motifs, delta, ties, kernels.generic) == want


ENGINES = [dict(engine="levels"), dict(engine="levels", bucketed=False), dict(engine="fused"), dict(engine="sql"), dict(engine="slabs", slab_width=3), dict(engine="slabs", slab_width=4, replicas=2, kernel="generic"), dict(engine="slabs", slab_width=100, split_siblings=1), dict(engine="slabs", slab_width=7, split_siblings=9, kernel="generic"), dict(engine="slabs", target_edges=5, hot_edges=2), dict(engine="hybrid", slab_width=5, budget=7, least_work=3), dict(engine="hybrid", target_edges=9, budget=5, least_work=0, split_siblings=1), dict(engine="hybrid", slab_width=100, budget=4, least_work=0, offload="one"), dict(engine="levels", independent=True)]


@pytest.mark.parametrize("options", ENGINES, ids=str)
def test_engines_agree_with_brute_force(spark, options):
    rng = random.Random(99)
    motifs = [*group("C2"), MOTIFS["burst2"], LOOPS[1], LOOPS[3], Motif.parse("same", "XY YZ ZX")]
    for ties in ("strict", "sequence"):
        rows = [(k, rng.randrange(5), rng.randrange(5), rng.randrange(16), k) for k in range(18)]
        spec = MineSpec(graph(spark, rows), motifs, 6, ties=ties, **options)
        want = {m.name: brute.matches(rows, m, 6, ties) for m in motifs}
        assert counts(mine(spec)) == {k: len(v) for k, v in want.items()}
        found = mine(replace(spec, mode="enumerate")).collect()
        assert sorted((r.motif, r.edge_path) for r in found) == sorted((m, "-".join(map(str, e))) for m, v in want.items() for e in v)


def test_empty_graph_has_rows(spark):
    for options in (dict(engine="levels"), dict(engine="slabs"), dict(engine="sql"), dict()):
        assert counts(mine(MineSpec(graph(spark, []), group("F2"), 5, **options))) == {"tri_cycle": 0, "tri_ff": 0, "path3": 0}


@pytest.mark.parametrize("width", [1, 2, 5, 10, 100])
@pytest.mark.parametrize("replicas", [1, 3])
def test_slab_borders(spark, width, replicas):
    rows = read(FIXTURES["F9"][0])
    for delta, _, want in FIXTURES["F9"][1]:
        got = counts(mine(MineSpec(graph(spark, rows), list(MOTIFS.values()), delta, engine="slabs", slab_width=width, replicas=replicas)))
        assert {k: v for k, v in got.items() if v} == want


def test_negative_times_and_quantile_borders(spark):
    rows = [(k, k % 3, (k + 1) % 3, k - 50, k) for k in range(100)]
    g = graph(spark, rows)
    want = counts(mine(MineSpec(g, group("F3"), 5, engine="levels")))
    assert want["tri_cycle"] == 98 + 95 + 95  # the second or third edge may come a round later
    for mode in ("quantile", "width"):
        assert counts(mine(MineSpec(g, group("F3"), 5, engine="slabs", target_edges=15, slab_mode=mode))) == want


def test_reference_counts(spark, sf_dir):
    """Counts of the survey on the smallest tables."""
    want = {"path2": 1791, "path3": 1645, "tri_cycle": 146, "tri_ff": 145, "lollipop": 90, "quad_cycle": 83, "lollipop_ret": 3, "pingpong2": 131, "pingpong3": 7, "burst2": 118, "out_star3": 1599, "in_star3": 1494, "bifan": 94, "scatter_gather": 70}
    g = from_tables(spark, sf_dir, "msg")
    assert counts(mine(MineSpec(g, list(MOTIFS.values()), "24 h", engine="slabs", target_edges=300))) == want
    assert counts(mine(MineSpec(g, list(MOTIFS.values()), DAY, engine="fused"))) == want
    trade = counts(mine(MineSpec(from_tables(spark, sf_dir, "trade"), list(MOTIFS.values()), "14 days", engine="levels", prune=True)))
    assert trade["path2"] == 4671 and trade["in_star3"] == 9645 and all(trade[m] == 0 for m in ("tri_cycle", "tri_ff", "lollipop", "lollipop_ret"))


def test_invariants(spark, sf_dir):
    g = from_tables(spark, sf_dir, "msg")
    spec = MineSpec(g, group("C3"), DAY, engine="slabs")
    base = counts(mine(spec))
    less = counts(mine(replace(spec, delta=DAY // 2)))
    assert all(less[m] <= base[m] for m in base)  # windows nest
    moved = TemporalGraph(g.edges.withColumn("t", F.col("t") + 12_345).withColumn("src", F.col("src") * 7 + 1).withColumn("dst", F.col("dst") * 7 + 1))
    assert counts(mine(replace(spec, graph=moved))) == base
    assert counts(mine(replace(spec, motifs=[*group("C3"), MOTIFS["bifan"]]))).items() >= base.items()
    rows = mine(replace(spec, mode="enumerate", engine="levels")).groupBy("motif").agg(F.count("*").alias("n"), F.countDistinct("edge_path").alias("d")).collect()
    assert {r.motif: r.n for r in rows} == {k: v for k, v in base.items() if v} and all(r.n == r.d for r in rows)
    compact, words = g.compact()
    assert counts(mine(replace(spec, graph=compact))) == base and words.count() == 15


def test_work_is_shared(spark, sf_dir):
    g = from_tables(spark, sf_dir, "msg")
    for name in GROUPS:
        r = measures.work_ratio(MineSpec(g, group(name), DAY), name).collect()[0]
        assert r.independent > r.shared > 0


def test_work_ratios_of_the_survey(spark, sf_dir):
    want = {"walkthrough": (138_761, 53_985), "F3": (223_713, 54_161), "C1": (150_830, 121_055)}
    g = from_tables(spark, sf_dir.replace("sf0.001", "sf0.01"), "msg")
    for name, pair in want.items():
        r = measures.work_ratio(MineSpec(g, group(name), DAY), name).collect()[0]
        assert (r.independent, r.shared) == pair


def test_labels_windows_and_scopes(spark):
    rows = [(0, 1, 2, 1, 0), (1, 2, 3, 2, 1), (2, 3, 1, 3, 2), (3, 1, 2, 4, 3)]
    v = spark.createDataFrame([(1, "x"), (2, "y"), (3, "x")], "vid bigint, vlabel string")
    g = TemporalGraph(spark.createDataFrame(rows, EDGES), v)
    m = [MOTIFS["path2"], Motif("xy", MOTIFS["path2"].edges).with_label(0, "x").with_label(1, "y")]
    for engine in ("levels", "slabs", "sql"):
        assert counts(mine(MineSpec(g, m, 10, engine=engine))) == {"path2": 3, "xy": 1}
    assert [window(x) for x in ("12 h", "1 day", "3.6 ms", 5)] == [DAY // 2, DAY, 3600, 5]
    for bad in ("soon", 0, -1):
        with pytest.raises(ValueError):
            window(bad)
    with pytest.raises(ValueError):
        mine(MineSpec(g, m, 10, engine="none"))


def test_epochs_deal_out_what_is_left(spark):
    """A hub: one receiver in one slab; the work is handed over, cut, and done by others, once."""
    rows = [(k, k % 7 + 1, 0, k, k) for k in range(60)] + [(100 + k, 0, k % 7 + 1, 60 + k, 100 + k) for k in range(60)]
    g, motifs = graph(spark, rows), group("C1")
    tree = PrefixTree.build(motifs)
    want = {m.name: len(brute.matches(rows, m, 40)) for m in motifs}
    for options in (dict(split_siblings=True), dict(split_siblings=False), dict(offload="one")):
        r = epochs.run(g.edges, tree, 40, balance.Slabs(40, 1000), budget=500, least_work=100, **options)
        assert {x.motif: x.n for x in r.found.collect()} == {k: v for k, v in want.items() if v}
        assert len(r.costs) > 2 and r.costs[0][1] > 1 and r.costs[0][3] > 1 and r.costs[-1][1] == 0


def test_pieces_bound_a_hub():
    """A receiver with 8,000 in-edges in one window: 32 million candidate pairs, a bounded block at a time."""
    import tracemalloc

    n = 8_000
    z = np.zeros(n, dtype=np.int64)
    a = kernels.Adjacency(np.arange(n), np.arange(1, n + 1), z, np.arange(n), np.arange(n))
    tree = PrefixTree.build([Motif.parse("in2", "AB CB")])
    for make in (kernels.generic, kernels.specialised):
        tracemalloc.start()
        assert kernels.tally(make(tree), a, np.ones(n, dtype=bool), n) == {"in2": n * (n - 1) // 2}
        assert tracemalloc.get_traced_memory()[1] < 200e6
        tracemalloc.stop()


def test_last_edges_are_counted_by_rank():
    """A closed last edge is no list when only counts are asked for."""
    assert "spans" in kernels.source(PrefixTree.build(group("F1")))
    rows = read(FIXTURES["F6"][0])
    for make in (kernels.generic, kernels.specialised):
        a = kernels.Adjacency(*(np.array([r[k] for r in rows], dtype=np.int64) for k in range(5)))
        t, owned = PrefixTree.build(list(MOTIFS.values())), np.ones(len(rows), dtype=bool)
        listed: dict[str, int] = {}
        for q, e in kernels.found(make(t), a, owned, 10):
            listed[q] = listed.get(q, 0) + len(e[0])
        assert listed == kernels.tally(make(t), a, owned, 10)


def test_split_trees_are_the_tree():
    for g in GROUPS:
        t = PrefixTree.build(group(g))
        for levels in (0, 1, 2, 9):
            parts = t.split(levels)
            names = [q for p in parts for q in p.query_of().values()]
            assert sorted(names) == sorted(t.query_of().values())
            assert {x for p in parts for x in p.prefixes()} == set(t.prefixes())
        assert all(len(n.children) < 2 for p in parts for n, _ in p.nodes())


def test_planned_slabs(spark):
    """Borders follow the edges, bursts are cut, hot slabs alone are copied; the index is a lookup."""
    rows = [(k, k % 9, (k + 1) % 9, k * 10, k) for k in range(500)] + [(1000 + k, k % 9, (k + 2) % 9, 6000 + k // 40, 1000 + k) for k in range(2000)] + [(5000, 1, 2, 900_000, 5000)]
    g = graph(spark, rows)
    h = balance.histogram(g.edges)
    assert h.n == 2501 and h.widest_window(50) >= 2000
    cut = balance.plan_slabs(g.edges, 10, 200)
    owned = {r.slab: r.n for r in cut.assigned(g.edges).where("owned").groupBy("slab").count().withColumnRenamed("count", "n").collect()}
    assert len(owned) > 6 and sum(owned.values()) == 2501 and max(n for s, n in owned.items()) <= 2000
    hot = balance.salt_hot_slabs(g.edges, cut, 150)
    dealt = hot.assigned(g.edges).where("owned").groupBy("slab", "replica").count()
    assert dealt.agg({"count": "sum"}).first()[0] == 2501
    many = dict(hot.hot)
    assert many and all((n > 150) == (s in many) for s, n in owned.items())
    want = counts(mine(MineSpec(g, group("F2"), 10, engine="levels")))
    assert counts(mine(MineSpec(g, group("F2"), 10, engine="slabs", target_edges=200, hot_edges=150))) == want
    assert counts(mine(MineSpec(g, group("F2"), 10, engine="slabs", target_edges=200, hot_work=500))) == want
    borders = tuple(range(0, 900_001, 220))
    assert len(borders) > 4_000
    got = g.edges.select("t", balance.Slabs(10, None, borders).index(F.col("t")).alias("s")).collect()
    assert all(r.s == sum(b <= r.t for b in borders) for r in got[::50])


def test_parallel_edges_have_ids_of_their_own(spark):
    df = spark.createDataFrame([(1, 2, 5), (1, 2, 5), (2, 3, 6), (2, 3, 6), (2, 3, 7)], "a int, b int, at int")
    from motifspark.graph import from_edge_list

    g = from_edge_list(df, "a", "b", "at")
    assert g.repeated_ids().count() == 0
    found = mine(MineSpec(g, [MOTIFS["path2"]], 10, mode="enumerate", engine="fused")).collect()
    assert len({r.edge_path for r in found}) == len(found) == 6
    assert from_edge_list(df, "a", "b", "at", repeats=False).repeated_ids().count() == 2


def test_stored_layout(spark, sf_dir):
    """A bucketed adjacency: the fused engine reads it and does not shuffle the edges."""
    g = from_tables(spark, sf_dir, "msg")
    spark.sql("drop table if exists layout_msg")
    layout = g.store_layout("layout_msg", DAY, 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        spec = MineSpec(g, group("F1"), DAY, engine="fused")
        stored = mine(replace(spec, layout=layout))
        assert counts(stored) == counts(mine(spec))
        assert measures.exchanges(stored) < measures.exchanges(mine(spec))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("drop table layout_msg")


def test_auto_follows_the_heuristic(spark, sf_dir):
    from motifspark.api import followed, pick_engine

    trade = MineSpec(from_tables(spark, sf_dir, "trade"), group("F1"), 7 * DAY)
    got = followed(trade, PrefixTree.build(trade.motifs))
    assert got.prune and not got.independent
    msg = MineSpec(from_tables(spark, sf_dir, "msg"), group("C1"), DAY, resources="constrained")
    assert followed(msg, PrefixTree.build(msg.motifs)).independent
    free = replace(msg, resources="plenty", window_choice=(DAY, DAY // 2))
    assert window(followed(free, PrefixTree.build(free.motifs)).delta) == DAY // 2
    assert pick_engine(msg) == "fused"
    assert counts(mine(msg)) == counts(mine(replace(msg, engine="levels")))
    burst = balance.Histogram(0, 10**12, 10**7, np.array([10_000_000, *[1] * 99_999]))
    assert pick_engine(msg, burst) == "fused" and pick_engine(msg, replace(burst, counts=np.full(100_000, 100))) == "slabs"


def test_results_own_their_frames(spark):
    g = graph(spark, read(FIXTURES["F6"][0]))
    a, b = (mine(MineSpec(g, group("D2"), 10, engine="levels")) for _ in range(2))
    assert a.held_frames and b.held_frames
    release(a)
    assert not a.held_frames and b.held_frames[0].is_cached
    release(b)


def test_bipartite(spark):
    line = [(k, k, k + 1, k, k) for k in range(12)]
    assert graph(spark, line).is_bipartite()
    assert not graph(spark, [*line, (20, 0, 12, 5, 20), (21, 12, 1, 5, 21)]).is_bipartite()
    assert graph(spark, [*line, (20, 0, 11, 5, 20)]).is_bipartite()
    assert not graph(spark, [(0, 1, 1, 1, 0)]).is_bipartite()


def test_plans(spark, sf_dir):
    """No step is a nested loop, and shared frontiers are read from where they are persisted."""
    g = TemporalGraph(readers.roundtrip(from_tables(spark, sf_dir, "msg").edges, "parquet").withColumn("edge_id", F.col("t")).withColumn("tie", F.col("t")))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        spec = MineSpec(g, group("F3"), DAY, engine="levels")
        shared = mine(spec)
        text = shared._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "NestedLoopJoin" not in text and "InMemoryTableScan" in text
        release(shared)
        alone = mine(replace(spec, independent=True))
        assert "CartesianProduct" not in alone._jdf.queryExecution().executedPlan().toString()
        shared = mine(spec)
        few = Fused(g.edges, PrefixTree.build(spec.motifs), DAY)
        assert len(few.frames) == 4
        text = few.counts()._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "NestedLoopJoin" not in text
        assert measures.exchanges(mine(replace(spec, engine="fused"))) < measures.exchanges(alone)
        assert len(Frontiers(g.edges, PrefixTree.build(spec.motifs), DAY).frames) == 7 < sum(map(len, spec.motifs)) == 17
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_baselines(spark, sf_dir):
    g = from_tables(spark, sf_dir, "msg")
    assert counts(baselines.static_then_filter(g.edges, MOTIFS["tri_cycle"], DAY)) == {"tri_cycle": 146}
    assert counts(baselines.sql_join(g.edges, MOTIFS["tri_cycle"], DAY)) == {"tri_cycle": 146}
    r = {x.kind: x.n for x in baselines.unordered(g.edges, DAY).collect()}
    assert r["in_order"] == 146 < r["any_order"]


def test_subsample_and_halo(spark):
    rows = [(k, k % 3, (k + 1) % 3, k, k) for k in range(100)]
    g = graph(spark, rows)
    assert g.subsample(0.5).edges.count() == 50 and 30 < g.subsample(0.5, "edges").edges.count() < 70
    assert balance.halo_factor(g.edges, balance.Slabs(5, 10)).collect()[0].copies == 150
    hot = balance.salt_hot_slabs(g.edges, balance.Slabs(5, 50), 20)
    assert hot.replicas == 1 and dict(hot.hot) == {0: 3, 1: 3}
