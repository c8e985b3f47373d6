"""The relational operators that mining needs around it, each as a query with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import oracles
from ..api import MineSpec, mine
from ..catalog import MOTIFS, group
from ..engines.levels import expand, release, root
from ..functions import exprs
from ..graph import DAY, from_tables
from ..plan import step
from ..sources import readers
from ..streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        release()
        return query(spark, sf_dir)

    QUERIES[name] = run
    if sql is not None:
        SQL[name] = sql


def msg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_tables(spark, sf_dir, "msg").edges


def found(spark: SparkSession, sf_dir: str, motifs=None) -> DataFrame:
    """Matches with their time, the input of the aggregations below."""
    return mine(MineSpec(from_tables(spark, sf_dir, "msg"), motifs or group("F2"), DAY, mode="enumerate", engine="levels"))


FOUND = "(" + oracles.matches("msg", group("F2"), DAY) + ")"
E = oracles.with_edges

# Sources
add("scan_pruned", lambda s, d: readers.events(s, d).where("ts >= TIMESTAMP_NTZ'2024-01-08' and ts < TIMESTAMP_NTZ'2024-01-15'").select("event_id", "user_id"), "SELECT event_id, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-08' AND ts < TIMESTAMP '2024-01-15'")
add("edge_list_roundtrip", lambda s, d: readers.roundtrip(msg(s, d)), E("msg", "SELECT src, dst, t FROM edges"))
add("scan_embeddings", lambda s, d: s.read.parquet(f"{d}/embeddings.parquet").groupBy("label").agg(F.count("*").alias("n"), F.max(F.size("embedding")).alias("dims")), "SELECT label, count(*) AS n, max(len(embedding)) AS dims FROM embeddings GROUP BY label")
add("scan_documents", lambda s, d: s.read.parquet(f"{d}/documents.parquet").select("lang", "n_chars").groupBy("lang").agg(F.count("*").alias("n"), F.max("n_chars").alias("longest")), "SELECT lang, count(*) AS n, max(n_chars) AS longest FROM documents GROUP BY lang")

# Filters, joins
add("filter_slice", lambda s, d: msg(s, d).where((F.col("etype") == "purchase") & F.col("src").isin(*range(0, 50, 5)) & F.col("etype").like("pur%")).select("edge_id", "src", "dst"), E("msg", "SELECT edge_id, src, dst FROM edges WHERE etype = 'purchase' AND src % 5 = 0 AND src < 50"))


def hop(s: SparkSession, d: str, **options) -> DataFrame:
    e = msg(s, d)
    p = MOTIFS["path2"].keys()
    return expand(root(e, step(p[:1]), False), e, p, DAY, "strict", False, **options).agg(F.count("*").alias("n"))


HOP = E("msg", f"SELECT count(*) AS n FROM edges a JOIN edges b ON b.src = a.dst AND b.dst <> a.src AND b.dst <> a.dst AND b.t > a.t AND b.t <= a.t + {DAY} WHERE a.src <> a.dst")
add("join_hash", lambda s, d: hop(s, d, hint="shuffle_hash"), HOP)
add("join_merge", lambda s, d: hop(s, d, hint="merge"), HOP)
add("join_broadcast", lambda s, d: hop(s, d, hint="broadcast"), HOP)
add("join_interval", lambda s, d: hop(s, d), HOP)
add("join_interval_bucketed", lambda s, d: hop(s, d, bucketed=True), HOP)
add(
    "join_theta",
    lambda s, d: (lambda n: n.alias("a").join(n.alias("b"), F.col("a.n_nationkey") < F.col("b.n_nationkey")).where("a.n_regionkey = b.n_regionkey").groupBy("a.n_regionkey").agg(F.count("*").alias("pairs")))(s.read.parquet(f"{d}/nation.parquet")),
    "SELECT a.n_regionkey, count(*) AS pairs FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey GROUP BY a.n_regionkey",
)
add(
    "join_asof",
    lambda s, d: exprs.as_of(msg(s, d).where("etype = 'purchase'"), msg(s, d).where("etype = 'view'"), "src", "t").select("edge_id", "prior_id"),
    E("msg", "SELECT a.edge_id, b.edge_id AS prior_id FROM (SELECT * FROM edges WHERE etype = 'purchase') a ASOF LEFT JOIN (SELECT * FROM edges WHERE etype = 'view') b ON a.src = b.src AND a.t > b.t"),
)


def starts(s: SparkSession, d: str) -> DataFrame:
    return found(s, d, [MOTIFS["tri_cycle"]]).select(F.split("edge_path", "-")[0].cast("long").alias("edge_id"))


TRI = "(" + oracles.matches("msg", [MOTIFS["tri_cycle"]], DAY) + ")"
add("semi_started", lambda s, d: msg(s, d).join(starts(s, d), "edge_id", "left_semi").select("edge_id", "src", "dst"), E("msg", f"SELECT edge_id, src, dst FROM edges WHERE edge_id IN (SELECT CAST(split_part(edge_path, '-', 1) AS BIGINT) FROM {TRI})"))
add(
    "anti_unmatched",
    lambda s, d: (lambda e: e.select(F.explode(F.array("src", "dst")).alias("vid")).distinct().join(e.join(starts(s, d), "edge_id").select(F.col("src").alias("vid")), "vid", "left_anti"))(msg(s, d)),
    E("msg", f"SELECT vid FROM (SELECT src AS vid FROM edges UNION SELECT dst FROM edges) WHERE vid NOT IN (SELECT src FROM edges WHERE edge_id IN (SELECT CAST(split_part(edge_path, '-', 1) AS BIGINT) FROM {TRI}))"),
)

# Aggregations
BY_DAY = f"SELECT motif, t_first // {DAY} AS day, t_last - t_first AS span FROM {FOUND}"


def by_day(s: SparkSession, d: str) -> DataFrame:
    return found(s, d).select("motif", F.expr(f"t_first div {DAY}").alias("day"), (F.col("t_last") - F.col("t_first")).alias("span"))


add("agg_distinct_vertices", lambda s, d: msg(s, d).groupBy("etype").agg(F.countDistinct("src").alias("senders"), (F.abs(F.approx_count_distinct("src", 0.01) / F.countDistinct("src") - 1) < 0.1).alias("approx_ok")), E("msg", "SELECT etype, count(DISTINCT src) AS senders, true AS approx_ok FROM edges GROUP BY etype"))
add("agg_rollup", lambda s, d: by_day(s, d).rollup("motif", "day").agg(F.count("*").alias("n")), f"SELECT motif, day, count(*) AS n FROM ({BY_DAY}) GROUP BY ROLLUP (motif, day)")
add("agg_cube", lambda s, d: msg(s, d).withColumn("loop", F.col("src") == F.col("dst")).cube("etype", "loop").agg(F.count("*").alias("n")), E("msg", "SELECT etype, src = dst AS loop, count(*) AS n FROM edges GROUP BY CUBE (etype, loop)"))


def grouping_sets(s: SparkSession, d: str) -> DataFrame:
    return s.sql("SELECT motif, day, count(*) AS n FROM {x} GROUP BY GROUPING SETS ((motif), (day), ())", x=by_day(s, d))


add("agg_gsets", grouping_sets, f"SELECT motif, day, count(*) AS n FROM ({BY_DAY}) GROUP BY GROUPING SETS ((motif), (day), ())")
NAMES = [m.name for m in group("F2")]
add("agg_pivot", lambda s, d: by_day(s, d).groupBy("day").pivot("motif", NAMES).agg(F.count("span")).na.fill(0, NAMES), f"SELECT day, {', '.join(f'''count(*) FILTER (WHERE motif = '{n}') AS {n}''' for n in NAMES)} FROM ({BY_DAY}) GROUP BY day")
add("agg_span_quantiles", lambda s, d: by_day(s, d).groupBy("motif").agg(F.round(F.expr("percentile(span, 0.5)"), 3).alias("median"), F.round(F.expr("percentile(span, 0.9)"), 3).alias("p90"), F.round(F.exp(F.avg(F.log("span"))), 0).alias("geomean")), f"SELECT motif, round(quantile_cont(span, 0.5), 3) AS median, round(quantile_cont(span, 0.9), 3) AS p90, round(exp(avg(ln(span))), 0) AS geomean FROM ({BY_DAY}) GROUP BY motif")

# Windows


def sent():
    """A sender's edges in time order."""
    return W.partitionBy("src").orderBy("t")


add(
    "win_rank",
    lambda s, d: msg(s, d).groupBy("etype", "src").agg(F.count("*").alias("n")).select("etype", "src", *(f().over(W.partitionBy("etype").orderBy(F.desc("n"))).alias(k) for k, f in (("rank", F.rank), ("dense", F.dense_rank))), F.ntile(4).over(W.partitionBy("etype").orderBy(F.desc("n"), "src")).alias("quarter")),
    E("msg", "SELECT etype, src, rank() OVER (PARTITION BY etype ORDER BY n DESC) AS rank, dense_rank() OVER (PARTITION BY etype ORDER BY n DESC) AS dense, ntile(4) OVER (PARTITION BY etype ORDER BY n DESC, src) AS quarter FROM (SELECT etype, src, count(*) AS n FROM edges GROUP BY etype, src)"),
)
add("win_gap", lambda s, d: msg(s, d).select("edge_id", (F.col("t") - F.lag("t").over(sent())).alias("gap"), F.lead("edge_id").over(sent()).alias("next_id"), F.first("edge_id").over(sent()).alias("first_id")), E("msg", "SELECT edge_id, t - lag(t) OVER w AS gap, lead(edge_id) OVER w AS next_id, first_value(edge_id) OVER w AS first_id FROM edges WINDOW w AS (PARTITION BY src ORDER BY t)"))
add("win_trailing", lambda s, d: msg(s, d).select("edge_id", F.count("*").over(sent().rangeBetween(-DAY, 0)).alias("n")), E("msg", f"SELECT edge_id, count(*) OVER (PARTITION BY src ORDER BY t RANGE BETWEEN {DAY} PRECEDING AND CURRENT ROW) AS n FROM edges"))

# Sorting, sets
add("topk_vertices", lambda s, d: msg(s, d).groupBy("src").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "src").limit(10), E("msg", "SELECT src, count(*) AS n FROM edges GROUP BY src ORDER BY n DESC, src LIMIT 10"))


def window_pair(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    g = from_tables(s, d, "msg")
    wide, narrow = (mine(MineSpec(g, group("F1"), x, mode="enumerate", engine="levels")).select("motif", "edge_path") for x in (DAY, DAY // 2))
    return wide, narrow


WIDE, NARROW = (f"(SELECT motif, edge_path FROM ({oracles.matches('msg', group('F1'), x)}))" for x in (DAY, DAY // 2))
add("set_union", lambda s, d: (lambda p: p[0].union(p[1]).distinct())(window_pair(s, d)), f"SELECT * FROM {WIDE} UNION SELECT * FROM {NARROW}")
add("set_intersect", lambda s, d: (lambda p: p[0].intersect(p[1]))(window_pair(s, d)), f"SELECT * FROM {WIDE} INTERSECT SELECT * FROM {NARROW}")
add("set_except", lambda s, d: (lambda p: p[0].exceptAll(p[1]))(window_pair(s, d)), f"SELECT * FROM {WIDE} EXCEPT ALL SELECT * FROM {NARROW}")

# Functions
add(
    "fn_string",
    lambda s, d: s.read.parquet(f"{d}/part.parquet").select("p_partkey", F.size(F.split("p_name", " ")).alias("words"), F.regexp_extract("p_name", "^(..)", 1).alias("first"), F.upper(F.substring("p_brand", 1, 3)).alias("tag"), F.concat_ws(">", F.split("p_name", " ")).alias("path")),
    "SELECT p_partkey, len(string_split(p_name, ' ')) AS words, substr(p_name, 1, 2) AS first, upper(substr(p_brand, 1, 3)) AS tag, replace(p_name, ' ', '>') AS path FROM part",
)
add("fn_date", lambda s, d: readers.events(s, d).groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), F.hour("ts").alias("hour")).agg(F.count("*").alias("n")), "SELECT strftime(ts, '%Y-%m-%d') AS day, hour(ts) AS hour, count(*) AS n FROM events GROUP BY ALL")
add("fn_math", lambda s, d: msg(s, d).select("edge_id", F.round(F.log1p("weight"), 6).alias("ln"), F.round(F.sqrt("weight"), 6).alias("root"), F.pmod("edge_id", F.lit(7)).alias("m")), E("msg", "SELECT edge_id, round(ln(1 + weight), 6) AS ln, round(sqrt(weight), 6) AS root, edge_id % 7 AS m FROM edges"))
add(
    "fn_array",
    lambda s, d: found(s, d, group("F1")).select("motif", F.transform(F.split("edge_path", "-"), lambda x: x.cast("long")).alias("ids")).select("motif", F.posexplode("ids").alias("pos", "edge_id")).groupBy("motif", "pos").agg(F.countDistinct("edge_id").alias("n"), F.min("edge_id").alias("least")),
    f"SELECT motif, pos - 1 AS pos, count(DISTINCT edge_id) AS n, min(edge_id) AS least FROM (SELECT motif, unnest(range(1, 4)) AS pos, CAST(unnest(string_split(edge_path, '-')) AS BIGINT) AS edge_id FROM ({oracles.matches('msg', group('F1'), DAY)})) GROUP BY motif, pos",
)
add("fn_map", lambda s, d: msg(s, d).select("edge_id", F.create_map(F.lit("etype"), F.col("etype"), F.lit("loop"), (F.col("src") == F.col("dst")).cast("string")).alias("attrs")).select("edge_id", F.col("attrs")["etype"].alias("etype"), F.element_at("attrs", "loop").alias("loop"), F.size(F.map_keys("attrs")).alias("n")), E("msg", "SELECT edge_id, etype, CAST(src = dst AS VARCHAR) AS loop, 2 AS n FROM edges"))
add("fn_json", lambda s, d: readers.events(s, d).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"), F.to_json(F.struct(F.col("user_id").alias("u"))).alias("j")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, '{\"u\":' || user_id || '}' AS j FROM events")
add("fn_label_udf", lambda s, d: msg(s, d).select("edge_id", exprs.edge_label("src", "dst").alias("label")), E("msg", "SELECT edge_id, src || '>' || dst AS label FROM edges"))
add("udaf_chat", lambda s, d: from_tables(s, d, "chat").edges.groupBy("conv_id").agg(exprs.pingpongs("src", "dst", "t").alias("n")), E("chat", "SELECT conv_id, count(*) FILTER (WHERE back) AS n FROM (SELECT conv_id, src <> dst AND dst = lead(src) OVER w AND src = lead(dst) OVER w AS back FROM edges WINDOW w AS (PARTITION BY conv_id ORDER BY t)) GROUP BY conv_id"))
add("udtf_msg", lambda s, d: exprs.mined_by_sql(msg(s, d), group("F2"), DAY, 3 * DAY), oracles.counts("msg", group("F2"), DAY))

# Batch twins of the streaming windows
add("stream_tumbling", lambda s, d: windows.flat(windows.tumbling(windows.timed(readers.events(s, d)))), "SELECT epoch_us(date_trunc('day', ts)) AS w_start, event_type, count(*) AS n FROM events GROUP BY ALL")
add("stream_sliding", lambda s, d: windows.flat(windows.sliding(windows.timed(readers.events(s, d)))), "SELECT epoch_us(w) AS w_start, event_type, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 6 HOUR FOR k IN [0, 1, 2, 3]]) AS w, event_type FROM events) GROUP BY ALL")
add(
    "stream_session",
    lambda s, d: windows.flat(windows.sessions(windows.timed(readers.events(s, d))), "user_id"),
    "SELECT epoch_us(min(ts)) AS w_start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, k",
)
