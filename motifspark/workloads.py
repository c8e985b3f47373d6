"""The experiment workloads on the given tables: queries and their SQL twins, by name."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import balance, baselines, heuristic, kernels, measures, oracles
from .api import MineSpec, mine, with_zeros
from .catalog import EXPERIMENT, GROUPS, MOTIFS, group
from .engines import slabs as slab_engine
from .engines.levels import holding, release, tallied
from .graph import DAY, from_tables
from .motif import Motif
from .sources import readers
from .tree import PrefixTree

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
DELTA = {"msg": DAY, "msg_hub": DAY // 2, "msg_day": DAY, "trade": 7 * DAY, "nation": 3 * DAY, "chat": 4}


#: The result whose frames are still persisted.
_LAST: list[DataFrame] = []


def add(name: str, query: Query, sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        release(*_LAST)  # what the query before persisted
        with holding() as held:
            out = query(spark, sf_dir)
        held += getattr(out, "held_frames", [])
        out.held_frames = held
        _LAST[:] = [out]
        return out

    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


def spec(spark: SparkSession, sf_dir: str, graph: str, motifs: list[Motif], **options) -> MineSpec:
    options.setdefault("delta", DELTA[graph])
    return MineSpec(from_tables(spark, sf_dir, graph), motifs, **options)


def mining(name: str, graph: str, motifs: list[Motif], sql: str | None = None, **options) -> None:
    add(name, lambda s, d: mine(spec(s, d, graph, motifs, **options)), sql or oracles.counts(graph, motifs, options.get("delta", DELTA[graph]), options.get("ties", "strict"), options.get("anchored")))


# Graphs
for g in ("msg", "msg_hub", "trade", "nation"):
    add(f"edges_{g}", lambda s, d, g=g: from_tables(s, d, g).edges.select("src", "dst", "t"), oracles.GRAPHS[g].join(["SELECT src, dst, t FROM (", ")"]))
    add(
        f"profile_{g}",
        lambda s, d, g=g: from_tables(s, d, g).profile(),
        oracles.with_edges(g, "SELECT (SELECT count(*) FROM (SELECT src FROM edges UNION SELECT dst FROM edges)) AS vertices, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM edges)) AS static_edges, count(*) AS temporal_edges, count(*) FILTER (WHERE src = dst) AS self_loops, max(t) - min(t) AS span_us FROM edges"),
    )
add("bipartite_trade", lambda s, d: from_tables(s, d, "trade").two_sided().select(F.lit("trade").alias("graph"), "bipartite"), oracles.with_edges("trade", "SELECT 'trade' AS graph, count(*) FILTER (WHERE (src < 0) = (dst < 0)) = 0 AS bipartite FROM edges"))


def tested_bipartite(s: SparkSession, d: str, kind: str) -> DataFrame:
    g = from_tables(s, d, kind)
    g.sides = None  # looked at, not declared
    return s.createDataFrame([(kind, g.is_bipartite())], "graph string, bipartite boolean")


add("bipartite_trade_tested", lambda s, d: tested_bipartite(s, d, "trade"), "SELECT 'trade' AS graph, true AS bipartite")
add("bipartite_msg", lambda s, d: tested_bipartite(s, d, "msg"), oracles.with_edges("msg", "SELECT 'msg' AS graph, count(*) = 0 AS bipartite FROM edges WHERE src = dst"))
add(
    "compact_roundtrip",
    lambda s, d: (lambda cw: cw[0].edges.join(cw[1].toDF("src_id", "src"), "src").join(cw[1].toDF("dst_id", "dst"), "dst").select("edge_id", F.col("src_id").alias("src"), F.col("dst_id").alias("dst")))(from_tables(s, d, "msg").compact()),
    oracles.with_edges("msg", "SELECT edge_id, src, dst FROM edges"),
)
add("layout_sorted", lambda s, d: from_tables(s, d, "msg").layouts("src").groupBy("src").agg(F.count("*").alias("n"), F.min("t").alias("t_first"), F.max("t").alias("t_last")), oracles.with_edges("msg", "SELECT src, count(*) AS n, min(t) AS t_first, max(t) AS t_last FROM edges GROUP BY src"))
add(
    "subsample_span",
    lambda s, d: from_tables(s, d, "msg").subsample(0.375).profile().select("temporal_edges"),
    oracles.with_edges("msg", "SELECT count(*) AS temporal_edges FROM edges WHERE t <= (SELECT min(t) + CAST(trunc((max(t) - min(t)) * 0.375) AS BIGINT) FROM edges)"),
)
add("clean_edges", lambda s, d: from_tables(s, d, "nation").cleaned(False).edges.select("src", "dst", "t").distinct(), oracles.with_edges("nation", "SELECT DISTINCT src, dst, t FROM edges WHERE src <> dst AND t >= 0"))

# Trees: the rows expected are written out by hand
TREES = {
    "tree_walkthrough": ("walkthrough", [("AB BC", None, 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC CD", "AB BC", 3, None), ("AB BC CD DB", "AB BC CD", 4, "lollipop"), ("AB BC CD DA", "AB BC CD", 4, "quad_cycle")]),
    "tree_D1": ("D1", [("AB BC CD", None, 3, "path3"), ("AB BC CD DB", "AB BC CD", 4, "lollipop"), ("AB BC CD DB BA", "AB BC CD DB", 5, "lollipop_ret")]),
    "tree_D2": ("D2", [("AB BC", None, 2, "path2"), ("AB BC CD", "AB BC", 3, "path3"), ("AB BC CD DB", "AB BC CD", 4, "lollipop"), ("AB BC CD DB BA", "AB BC CD DB", 5, "lollipop_ret")]),
    "tree_F1": ("F1", [("AB BC", None, 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC AC", "AB BC", 3, "tri_ff")]),
    "tree_F2": ("F2", [("AB BC", None, 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC AC", "AB BC", 3, "tri_ff"), ("AB BC CD", "AB BC", 3, "path3")]),
    "tree_F3": ("F3", [("AB BC", None, 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC AC", "AB BC", 3, "tri_ff"), ("AB BC CD", "AB BC", 3, "path3"), ("AB BC CD DB", "AB BC CD", 4, "lollipop"), ("AB BC CD DA", "AB BC CD", 4, "quad_cycle")]),
    "tree_C1": ("C1", [("AB", None, 1, None), ("AB CB DB", "AB", 3, "in_star3"), ("AB AC AD", "AB", 3, "out_star3"), ("AB BA AB", "AB", 3, "pingpong3"), ("AB BC CA", "AB", 3, "tri_cycle")]),
    "tree_C2": ("C2", [("AB", None, 1, None), ("AB BA AB", "AB", 3, "pingpong3"), ("AB CB CD AD", "AB", 4, "bifan"), ("AB BC", "AB", 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC CD", "AB BC", 3, "path3"), ("AB BC CD DB", "AB BC CD", 4, "lollipop")]),
    "tree_C3": ("C3", [("AB", None, 1, None), ("AB BA AB", "AB", 3, "pingpong3"), ("AB AC BD CD", "AB", 4, "scatter_gather"), ("AB BC", "AB", 2, None), ("AB BC CA", "AB BC", 3, "tri_cycle"), ("AB BC AC", "AB BC", 3, "tri_ff"), ("AB BC CD", "AB BC", 3, "path3"), ("AB BC CD DB", "AB BC CD", 4, "lollipop"), ("AB BC CD DA", "AB BC CD", 4, "quad_cycle"), ("AB BC CD DB BA", "AB BC CD DB", 5, "lollipop_ret")]),
}
COLUMNS = "node, parent, n_edges, query"


def values(rows: list[tuple], columns: str) -> str:
    said = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(said, r)) + ')' for r in rows)}) AS x({columns})"


def tree(name: str, motifs: list[Motif], rows: list[tuple]) -> None:
    add(name, lambda s, d: PrefixTree.build(motifs).to_df(s), values(rows, COLUMNS))


#: Trees whose nodes come with their partial matches in the graph.
COUNTED = ("tree_C1", "tree_C2", "tree_C3", "tree_D1", "tree_D2")


def counted_tree(name: str, motifs: list[Motif], rows: list[tuple]) -> None:
    nodes = [Motif.parse(r[0], r[0]) for r in rows]
    add(
        name,
        lambda s, d: PrefixTree.build(motifs).to_df(s).join(F.broadcast(mine(spec(s, d, "msg", [Motif.parse(n.text, n.text) for n, _ in PrefixTree.build(motifs).nodes()], engine="slabs", target_edges=100_000)).toDF("node", "partials")), "node").select("node", "parent", "n_edges", "query", "partials"),
        f"SELECT {COLUMNS}, n AS partials FROM ({values(rows, COLUMNS)}) JOIN ({oracles.counts('msg', nodes, DAY)}) ON motif = node",
    )


for key, (name, rows) in TREES.items():
    (counted_tree if key in COUNTED else tree)(key, group(name), rows)
tree("tree_single", [MOTIFS["tri_cycle"]], [("", None, 0, None), ("AB BC CA", "", 3, "tri_cycle")])
tree("tree_empty_root", [Motif.parse("loop_out", "AA AB"), MOTIFS["tri_cycle"]], [("", None, 0, None), ("AA AB", "", 2, "loop_out"), ("AB BC CA", "", 3, "tri_cycle")])
tree("tree_prefix_query", [MOTIFS["path2"], MOTIFS["path3"], MOTIFS["tri_cycle"]], [("AB BC", None, 2, "path2"), ("AB BC CD", "AB BC", 3, "path3"), ("AB BC CA", "AB BC", 3, "tri_cycle")])
add("tree_intermediates", lambda s, d: PrefixTree.build(group("C3")).to_df(s).where("query is null").select("node", "n_edges"), values([("AB", 1), ("AB BC", 2)], "node, n_edges"))
add("tree_table", lambda s, d: PrefixTree.build(group("C3")).to_df(s).groupBy("n_edges").agg(F.count("*").alias("nodes"), F.count("query").alias("queries")), values([(1, 1, 0), (2, 1, 0), (3, 4, 4), (4, 3, 3), (5, 1, 1)], "n_edges, nodes, queries"))
add(
    "tree_levels",
    lambda s, d: s.createDataFrame([(len(p),) for p in PrefixTree.build(group("C3")).prefixes()], "depth int").groupBy("depth").agg(F.count("*").alias("prefixes")),
    values([(1, 1), (2, 3), (3, 5), (4, 3), (5, 1)], "depth, prefixes"),
)
SIMILARITY = [("walkthrough", 0.4545), ("D1", 0.5833), ("D2", 0.6429), ("F1", 0.3333), ("F2", 0.4444), ("F3", 0.5882), ("C1", 0.25), ("C2", 0.4118), ("C3", 0.5517)]


def observed(s: SparkSession, d: str) -> DataFrame:
    """(day, pattern): what a sender did in a day, in order; the distinct ones of a day are a group of stars with an event type on each edge."""
    e = readers.events(s, d).select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id", F.struct("ts", "event_id", "event_type").alias("e"))
    return e.groupBy("day", "user_id").agg(F.transform(F.sort_array(F.collect_list("e")), lambda x: x["event_type"]).alias("pattern")).select("day", "pattern").distinct()


def of_days(s: SparkSession, d: str, number, column: str) -> DataFrame:
    """A number of each day's prefix tree."""

    def work(key, table):
        motifs = [Motif(f"m{k}", tuple((0, x + 1) for x in range(len(p))), tuple(f"etype = '{x}'" for x in p)) for k, p in enumerate(table.column("pattern").to_pylist())]
        return pa.table({"day": [key[0].as_py()], column: [number(PrefixTree.build(motifs))]})

    return observed(s, d).groupBy("day").applyInArrow(work, f"day string, {column} double")


OBSERVED = "SELECT DISTINCT day, pattern FROM (SELECT strftime(ts, '%Y-%m-%d') AS day, list(event_type ORDER BY ts, event_id) AS pattern FROM events GROUP BY day, user_id)"
PREFIXES = f"SELECT day, unnest(list_transform(range(1, len(pattern) + 1), lambda k: list_slice(pattern, 1, k))) AS prefix FROM ({OBSERVED})"
BY_PREFIX = f"SELECT day, round(1 - count(DISTINCT prefix) / count(*), 4) AS similarity FROM ({PREFIXES}) GROUP BY day"
add("similarity_all", lambda s, d: of_days(s, d, lambda t: t.similarity(), "similarity").select("day", F.round("similarity", 4).alias("similarity")), BY_PREFIX)


def prefix_similarity(s: SparkSession, d: str) -> DataFrame:
    """The measure as an aggregate over the table of prefixes."""
    p = observed(s, d).select("day", F.explode(F.transform(F.sequence(F.lit(1), F.size("pattern")), lambda k: F.slice("pattern", 1, k))).alias("prefix"))
    return p.groupBy("day").agg(F.round(1 - F.countDistinct("prefix") / F.count("*"), 4).alias("similarity"))


add("similarity_prefix", prefix_similarity, BY_PREFIX)

# Single motifs, groups, engines
for m in MOTIFS.values():
    mining(f"single_{m.name}", "msg", [m], engine="levels")
    mining(f"single_{m.name}_trade", "trade", [m], engine="levels")
for g in EXPERIMENT:
    mining(f"indep_{g}", "msg", group(g), engine="slabs", kernel="generic", independent=True)
    for graph in ("msg", "trade", "nation"):
        mining(f"comine_{g}_{graph}", graph, group(g), engine="levels")
    mining(f"fused_{g}", "msg", group(g), engine="fused")
    mining(f"slab_{g}", "msg", group(g), engine="slabs", target_edges=2_000)
    mining(f"sql_{g}", "msg", group(g), engine="sql")
    add(f"enum_{g}", lambda s, d, g=g: mine(spec(s, d, "msg", group(g), mode="enumerate", engine="levels")), oracles.matches("msg", group(g), DAY))
    add(f"work_{g}", lambda s, d, g=g: measures.work(spec(s, d, "msg", group(g)), g), oracles.work("msg", g, group(g), DAY))
    add(f"workratio_{g}", lambda s, d, g=g: measures.work_ratio(spec(s, d, "msg", group(g)), g), oracles.work("msg", g, group(g), DAY, True))
    add(f"enum_slab_{g}", lambda s, d, g=g: mine(spec(s, d, "msg", group(g), mode="enumerate", engine="slabs", target_edges=2_000)), oracles.matches("msg", group(g), DAY))
mining("comine_walkthrough_msg", "msg", group("walkthrough"), engine="levels")
add("work_walkthrough", lambda s, d: measures.work(spec(s, d, "msg", group("walkthrough")), "walkthrough"), oracles.work("msg", "walkthrough", group("walkthrough"), DAY))
mining("mine_auto", "msg", group("F3"))
mining("indep_salted", "msg_hub", group("F2"), engine="slabs", independent=True, replicas=3, target_edges=3_000)
add(
    "enum_top",
    lambda s, d: mine(spec(s, d, "msg", group("F2"), mode="enumerate", engine="levels", max_per_motif=3)),
    f"SELECT motif, edge_path, t_first, t_last FROM (SELECT *, row_number() OVER (PARTITION BY motif ORDER BY t_first, t_last, edge_path) AS r FROM ({oracles.matches('msg', group('F2'), DAY)})) WHERE r <= 3",
)

# Semantics
mining("ties_sequence", "msg_day", group("F3") + [MOTIFS["burst2"]], engine="levels", ties="sequence", delta=DAY // 2)
mining("ties_sequence_slab", "msg_day", group("F3") + [MOTIFS["burst2"]], engine="slabs", ties="sequence", delta=DAY // 2, target_edges=2_000)
mining("ties_strict_day", "msg_day", group("F3"), engine="levels", delta=DAY // 2)
bought = [m.with_predicate(0, "etype = 'purchase'") for m in group("F2")]
mining("attr_purchase_first", "msg", bought, engine="levels", sql=oracles.counts("msg", bought, DAY))
mixed = [MOTIFS["tri_cycle"], Motif("tri_big", MOTIFS["tri_cycle"].edges, (None, "weight > 50", None)), Motif("tri_ff_big", MOTIFS["tri_ff"].edges, (None, "weight > 50", None))]
mining("attr_mixed_predicates", "msg", mixed, engine="slabs", target_edges=2_000, sql=oracles.counts("msg", mixed, DAY))
mining("anchored", "msg", group("F3"), engine="levels", anchored="src < 10")
mining("anchored_slab", "msg", group("F3"), engine="slabs", target_edges=2_000, anchored="src < 10")
WINDOWS = {"tri_cycle": DAY // 4, "tri_ff": DAY // 2}
add("mixed_delta", lambda s, d: mine(spec(s, d, "msg", group("F2"), deltas=WINDOWS, engine="levels")), oracles.counts("msg", group("F2"), DAY, deltas=WINDOWS))
loops = [Motif.parse("loop", "AA"), Motif.parse("loop_out", "AA AB"), Motif.parse("in_loop", "AB BB"), Motif.parse("in_loop_back", "AB BB BA")]
mining("loop_motif", "msg", loops, engine="levels")
mining("loop_motif_slab", "msg", loops, engine="slabs", target_edges=2_000)
free = [Motif.parse("two_apart", "AB CD")]
mining("free_step", "msg", free, engine="levels", delta=DAY // 24)
mining("free_step_slab", "msg", free, engine="slabs", delta=DAY // 24, target_edges=2_000)
add("scoped_chat", lambda s, d: slab_engine.run_scoped(from_tables(s, d, "chat").edges, PrefixTree.build([MOTIFS["pingpong2"], MOTIFS["pingpong3"], MOTIFS["path2"]]), 4, "conv_id").where("n > 0"), f"SELECT * FROM ({oracles.scoped('chat', [MOTIFS['pingpong2'], MOTIFS['pingpong3'], MOTIFS['path2']], 4, 'conv_id')}) WHERE n > 0")
mining("bucketed_F3", "msg_hub", group("F3"), engine="levels", bucketed=True)

# Sweeps
for g in ("D2", "F3", "C3"):
    for name, delta in (("half", DAY // 2), ("one", DAY), ("double", 2 * DAY)):
        mining(f"delta_{g}_{name}", "msg", group(g), engine="slabs", delta=delta, target_edges=2_000)
for n in (1, 4, 8):
    mining(f"scale_{n}", "msg", group("C3")[:n], engine="slabs", target_edges=2_000)
for graph in ("msg", "trade", "nation"):
    edges = f"(SELECT count(*) FROM ({oracles.GRAPHS[graph]}))"
    add(f"density_{graph}", lambda s, d, graph=graph: measures.density(spec(s, d, graph, group("F3"), engine="levels")), f"SELECT motif, n, round(n / {edges}, 6) AS density FROM ({oracles.counts(graph, group('F3'), DELTA[graph])})")

# Balancing and kernels
HUB = {"engine": "slabs", "target_edges": 3_000}
mining("slab_quantile", "msg_hub", group("F2"), **HUB)
mining("slab_width", "msg_hub", group("F2"), slab_mode="width", **HUB)
mining("slab_salted", "msg_hub", group("F2"), replicas=3, **HUB)
mining("sibling_split", "msg_hub", group("F2"), split_siblings=1, **HUB)
mining("kernel_generic", "msg", group("C3"), engine="slabs", kernel="generic", target_edges=2_000)
mining("kernel_special", "msg", group("C3"), engine="slabs", kernel="special", target_edges=2_000)


mining("slab_salted_planned", "msg_hub", group("F2"), engine="slabs", target_edges=5_000, hot_edges=2_000)


# Every group on the even and on the skewed graph: epochs, siblings apart, contexts of all levels apart
for g in EXPERIMENT:
    for graph, tag in (("msg", ""), ("msg_hub", "_hub")):
        small = {"engine": "hybrid", "target_edges": 3_000, "budget": 4_000, "least_work": 2_000}
        mining(f"hybrid_{g}{tag}", graph, group(g), offload="one", **small)
        mining(f"multi_offload_{g}{tag}", graph, group(g), offload="all", split_siblings=1, **small)
        mining(f"sibling_split_{g}{tag}", graph, group(g), engine="slabs", target_edges=3_000, split_siblings=9)
add("enum_hybrid", lambda s, d: mine(spec(s, d, "msg", group("F3"), mode="enumerate", engine="hybrid", target_edges=3_000, budget=4_000, least_work=2_000, split_siblings=1)), oracles.matches("msg", group("F3"), DAY))
mining("hybrid_ties_sequence", "msg_day", group("F3") + [MOTIFS["burst2"]], engine="hybrid", ties="sequence", delta=DAY // 2, target_edges=2_000, budget=1_000, least_work=100, split_siblings=1)
mining("slab_work_balanced", "msg_hub", group("F3"), engine="slabs", target_edges=5_000, hot_work=20_000)


def arrays(s: SparkSession, d: str) -> DataFrame:
    """The ablation of flat columns: 3-cycles with the vertices in an array."""
    e = from_tables(s, d, "msg").edges.where("src <> dst")
    g = e.select(F.col("src").alias("g_src"), F.col("dst").alias("g_dst"), F.col("t").alias("g_t"))
    f = e.select(F.array("src", "dst").alias("v"), F.col("t").alias("t_first"), F.col("t").alias("t_last"))
    f = f.join(g, (F.col("g_src") == F.col("v")[1]) & (F.col("g_t") > F.col("t_last")) & (F.col("g_t") <= F.col("t_first") + DAY)).where(~F.array_contains("v", F.col("g_dst"))).select(F.concat("v", F.array("g_dst")).alias("v"), "t_first", F.col("g_t").alias("t_last"))
    f = f.join(g, (F.col("g_src") == F.col("v")[2]) & (F.col("g_dst") == F.col("v")[0]) & (F.col("g_t") > F.col("t_last")) & (F.col("g_t") <= F.col("t_first") + DAY))
    return f.agg(F.count("*").alias("n")).select(F.lit("tri_cycle").alias("motif"), "n")


add("layout_array", arrays, oracles.counts("msg", [MOTIFS["tri_cycle"]], DAY))
add(
    "halo_factor",
    lambda s, d: balance.halo_factor(from_tables(s, d, "msg").edges, balance.Slabs(DAY, 3 * DAY)),
    oracles.with_edges("msg", f"SELECT count(*) AS edges, CAST(sum(1 + t // {3 * DAY} - (t - {DAY}) // {3 * DAY}) AS BIGINT) AS copies, round(sum(1 + t // {3 * DAY} - (t - {DAY}) // {3 * DAY}) / count(*), 6) AS halo_factor FROM edges"),
)
add(
    "counter_modes",
    lambda s, d: measures.listed_and_counted(spec(s, d, "msg", group("F1"), engine="slabs", target_edges=2_000)),
    f"SELECT motif, n AS listed, n AS counted FROM ({oracles.counts('msg', group('F1'), DAY)})",
)
for g in ("D2", "F3", "C3"):
    add(f"probes_{g}", lambda s, d, g=g: measures.probes(spec(s, d, "msg", group(g)), g), oracles.probes("msg", g, group(g), DAY))
_OWN = f"1 + t // {3 * DAY} - (t - {DAY}) // {3 * DAY}"
add(
    "cost_balance",
    lambda s, d: measures.copies(
        from_tables(s, d, "msg").edges,
        {"slabs": (balance.Slabs(DAY, 3 * DAY), 1), "replicas": (balance.Slabs(DAY, 3 * DAY, (), 3), 1), "siblings": (balance.Slabs(DAY, 3 * DAY), len(PrefixTree.build(group("C3")).split(9)))},
    ),
    oracles.with_edges("msg", f"SELECT unnest(['slabs', 'replicas', 'siblings']) AS plan, count(*) AS edges, unnest([CAST(sum({_OWN}) AS BIGINT), CAST(3 * sum({_OWN}) AS BIGINT), CAST(6 * sum({_OWN}) AS BIGINT)]) AS copies FROM edges"),
)
for g in ("trade", "nation"):
    add(f"unique_ids_{g}", lambda s, d, g=g: from_tables(s, d, g).edges.agg(F.count("*").alias("edges"), F.countDistinct("edge_id").alias("ids")), oracles.with_edges(g, "SELECT count(*) AS edges, count(*) AS ids FROM edges"))
add(
    "distinct_forms",
    lambda s, d: (lambda e: e.crossJoin(F.broadcast(e.groupBy("src").agg(F.count("*").alias("k")).orderBy(F.desc("k"), "src").limit(1).select(F.col("src").alias("hub")))).agg(F.sum((~(F.col("src") == F.col("hub")) | (F.col("dst") != F.col("hub"))).cast("long")).alias("fused"), F.sum(F.when(F.col("src") == F.col("hub"), F.col("dst") != F.col("hub")).otherwise(True).cast("long")).alias("implied")))(from_tables(s, d, "msg").edges),
    oracles.with_edges("msg", "SELECT count(*) FILTER (WHERE NOT src = hub OR dst <> hub) AS fused, count(*) FILTER (WHERE CASE WHEN src = hub THEN dst <> hub ELSE true END) AS implied FROM edges, (SELECT src AS hub FROM edges GROUP BY src ORDER BY count(*) DESC, src LIMIT 1)"),
)
add("prune_trade", lambda s, d: mine(spec(s, d, "trade", group("C3"), engine="levels", prune=True)), oracles.counts("trade", group("C3"), DELTA["trade"]))

# Baselines
for m in ("tri_cycle", "tri_ff", "path2"):
    add(f"static_filter_{m}", lambda s, d, m=m: baselines.static_then_filter(from_tables(s, d, "msg").edges, MOTIFS[m], DAY), oracles.counts("msg", [MOTIFS[m]], DAY))
for m in ("path2", "tri_cycle", "lollipop", "quad_cycle"):
    add(f"sqljoin_{m}", lambda s, d, m=m: baselines.sql_join(from_tables(s, d, "msg").edges, MOTIFS[m], DAY), oracles.counts("msg", [MOTIFS[m]], DAY))
add("scan_share", lambda s, d: baselines.scan_sharing(spec(s, d, "msg", group("F2"))), oracles.counts("msg", group("F2"), DAY))
add(
    "unordered_overcount",
    lambda s, d: baselines.unordered(from_tables(s, d, "msg").edges, DAY),
    oracles.with_edges("msg", f"SELECT unnest(['any_order', 'in_order']) AS kind, unnest([count(*), count(*) FILTER (WHERE a.t < b.t AND b.t < c.t)]) AS n FROM edges a JOIN edges b ON b.src = a.dst AND b.dst <> a.src AND abs(b.t - a.t) <= {DAY} JOIN edges c ON c.src = b.dst AND c.dst = a.src WHERE a.src <> a.dst AND b.src <> b.dst AND c.src <> c.dst AND greatest(a.t, b.t, c.t) - least(a.t, b.t, c.t) <= {DAY}"),
)
add("approx_slab", lambda s, d: baselines.approximate(spec(s, d, "msg", group("F2")), 2 * DAY), oracles.counts("msg", group("F2"), DAY, anchored=f"(t // {2 * DAY}) % 2 = 0").join(["SELECT motif, n * 2 AS n FROM (", ")"]))


# Heuristic and measures
def advice(s: SparkSession, d: str) -> DataFrame:
    """What the heuristic says of each graph, whose edges tell whether it has sides, and group."""
    said = [(sides, g, b, *heuristic.advise(sides, PrefixTree.build(group(g)).similarity(), b)[:2]) for sides in (False, True) for g in EXPERIMENT for b in ("plenty", "constrained")]
    table = s.createDataFrame(said, "bipartite boolean, group_name string, backend string, co_mine boolean, reason string")
    seen = None
    for graph in ("msg", "nation", "trade"):
        row = from_tables(s, d, graph).two_sided().select(F.lit(graph).alias("graph"), "bipartite")
        seen = row if seen is None else seen.unionByName(row)
    return table.join(F.broadcast(seen), "bipartite").select("graph", "group_name", "backend", "co_mine", "reason")


add(
    "advise_all",
    advice,
    f"SELECT graph, group_name, backend, graph = 'trade' OR backend = 'plenty' OR similarity >= 0.44 AS co_mine, CASE WHEN graph = 'trade' THEN 'bipartite' WHEN backend = 'constrained' AND similarity < 0.44 THEN 'similarity below threshold' ELSE 'shared prefixes' END AS reason FROM ({values(SIMILARITY[1:], 'group_name, similarity')}), (SELECT unnest(['msg', 'nation', 'trade']) AS graph), (SELECT unnest(['plenty', 'constrained']) AS backend)",
)


def gains(s: SparkSession, d: str) -> DataFrame:
    """A row a graph and group: how much less work mining together is, and the work it takes."""
    out = None
    for graph in ("msg", "trade"):
        rows = measures.work_ratios(from_tables(s, d, graph), {g: group(g) for g in ("D2", "F3", "C3")}, DELTA[graph])
        rows = rows.select(F.lit(graph).alias("graph"), "group_name", (F.col("independent") / F.col("shared")).alias("gain"), F.col("shared").cast("double").alias("shared"))
        out = rows if out is None else out.unionByName(rows)
    return out


_GAINS = " UNION ALL ".join(f"SELECT '{graph}' AS graph, independent / shared AS gain, CAST(shared AS DOUBLE) AS shared FROM ({oracles.work(graph, g, group(g), DELTA[graph], True)})" for graph in ("msg", "trade") for g in ("D2", "F3", "C3"))
add("speedup_geomean", lambda s, d: measures.geomean(gains(s, d), "gain", ["graph"]), f"SELECT graph, round(exp(avg(ln(gain))), 6) AS geomean FROM ({_GAINS}) GROUP BY graph")
add("time_weighted", lambda s, d: measures.time_weighted(gains(s, d), "shared", "gain", ["graph"]), f"SELECT graph, round(sum(shared * gain) / sum(shared), 6) AS gain FROM ({_GAINS}) GROUP BY graph")
add(
    "kernel_source",
    lambda s, d: of_days(s, d, lambda t: float(kernels.source(t).count("a.candidates")), "joins").select("day", F.col("joins").cast("long").alias("joins")),
    f"SELECT day, count(DISTINCT prefix) FILTER (WHERE len(prefix) > 1) AS joins FROM ({PREFIXES}) GROUP BY day",
)
