"""DuckDB statements for the mining queries, one motif at a time; nothing here uses the prefix tree."""

from __future__ import annotations

from .motif import Motif

MSG = """SELECT event_id AS edge_id, CAST(user_id AS BIGINT) AS src, {dst} AS dst, {t} AS t, event_id AS tie, event_type AS etype, value AS weight FROM events"""
SPREAD = "(CAST(json_extract_string(props, '$.k') AS BIGINT) + 100 * (event_id % 15)) % (SELECT max(user_id) + 1 FROM events)"
HUB = "CAST(json_extract_string(props, '$.k') AS BIGINT) % (SELECT max(user_id) + 1 FROM events)"
TRADE = """SELECT 0 AS edge_id, CASE WHEN l_returnflag = 'R' THEN -1 - l_suppkey ELSE o_custkey END AS src,
 CASE WHEN l_returnflag = 'R' THEN o_custkey ELSE -1 - l_suppkey END AS dst, epoch_us(l_shipdate) AS t, 0 AS tie, l_returnflag AS etype, l_extendedprice AS weight
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey"""
NATION = """SELECT 0 AS edge_id, CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, epoch_us(l_shipdate) AS t, 0 AS tie, l_returnflag AS etype, l_extendedprice AS weight
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"""
CODE = "CASE {0} WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END"
CHAT = f"""SELECT a.conv_id * 100000 + a.turn AS edge_id, {CODE.format('a.role')} AS src, {CODE.format('b.role')} AS dst, a.turn AS t, a.conv_id * 100000 + a.turn AS tie, a.conv_id
 FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"""
GRAPHS = {
    "msg": MSG.format(dst=SPREAD, t="epoch_us(ts)"),
    "msg_hub": MSG.format(dst=HUB, t="epoch_us(ts)"),
    "msg_day": MSG.format(dst=SPREAD, t="epoch_us(date_trunc('day', ts))"),
    "trade": TRADE,
    "nation": NATION,
    "chat": CHAT,
}


def chain(motif: Motif, delta: int, ties: str = "strict", tag: str = "", anchored: str | None = None, scope: str | None = None, loose: bool = False) -> list[str]:
    """One materialised expression an edge position, named {tag}{position}."""
    out, bound = [], []
    for k, (u, v) in enumerate(motif.canonical().edges):
        where = motif.where[k]
        if k == 0:
            w = ["src = dst" if u == v else "src <> dst", *([f"({where})"] if where else []), *([f"({anchored})"] if anchored else [])]
            cols = "src AS v0" if u == v else "src AS v0, dst AS v1"
            bound = [0] if u == v else [0, 1]
            out.append(f"{tag}0 AS MATERIALIZED (SELECT CAST(edge_id AS VARCHAR) AS path, {cols}, t AS t_first, t AS t_last, tie AS tie_last{', ' + scope if scope else ''} FROM edges WHERE {' AND '.join(w)})")
            continue
        on = ["g.t > f.t_last" if ties == "strict" else "(g.t > f.t_last OR (g.t = f.t_last AND g.tie > f.tie_last))", f"g.t <= f.t_first + {delta}"]
        new = []
        for end, x in (("src", u), ("dst", v)):
            if x in bound:
                on.append(f"g.{end} = f.v{x}")
            elif not (end == "dst" and u == v):
                on += [f"g.{end} <> f.v{y}" for y in bound if not (loose and k == len(motif) - 1)]
                new.append((end, x))
        if u == v and u not in bound:
            on.append("g.src = g.dst")
        if len(new) == 2:
            on.append("g.src <> g.dst")
        if where:
            on.append(f"({where})")
        if scope:
            on.append(f"g.{scope} = f.{scope}")
        cols = [f"f.v{x}" for x in bound] + [f"g.{end} AS v{x}" for end, x in new]
        bound += [x for _, x in new]
        out.append(f"{tag}{k} AS MATERIALIZED (SELECT f.path || '-' || CAST(g.edge_id AS VARCHAR) AS path, {', '.join(cols)}, f.t_first, g.t AS t_last, g.tie AS tie_last{', f.' + scope if scope else ''} FROM {tag}{k - 1} f JOIN edges g ON {' AND '.join(on)})")
    return out


def _whole(graph: str, parts: list[str], end: str) -> str:
    return "WITH edges AS MATERIALIZED (" + GRAPHS[graph] + "),\n" + ",\n".join(parts) + "\n" + end


def counts(graph: str, motifs: list[Motif], delta: int, ties: str = "strict", anchored: str | None = None, deltas: dict[str, int] | None = None) -> str:
    parts, ends = [], []
    for i, m in enumerate(motifs):
        tag = f"m{i}_"
        parts += chain(m, (deltas or {}).get(m.name, delta), ties, tag, anchored)
        ends.append(f"SELECT '{m.name}' AS motif, count(*) AS n FROM {tag}{len(m) - 1}")
    return _whole(graph, parts, "\nUNION ALL ".join(ends))


def matches(graph: str, motifs: list[Motif], delta: int, ties: str = "strict") -> str:
    parts, ends = [], []
    for i, m in enumerate(motifs):
        tag = f"m{i}_"
        parts += chain(m, delta, ties, tag)
        ends.append(f"SELECT '{m.name}' AS motif, path AS edge_path, t_first, t_last FROM {tag}{len(m) - 1}")
    return _whole(graph, parts, "\nUNION ALL ".join(ends))


def scoped(graph: str, motifs: list[Motif], delta: int, scope: str) -> str:
    parts, ends = [], []
    for i, m in enumerate(motifs):
        tag = f"m{i}_"
        parts += chain(m, delta, "strict", tag, None, scope)
        ends.append(f"SELECT {scope}, '{m.name}' AS motif, count(*) AS n FROM {tag}{len(m) - 1} GROUP BY {scope}")
    return _whole(graph, parts, "\nUNION ALL ".join(ends))


def work(graph: str, group: str, motifs: list[Motif], delta: int, independent: bool = False) -> str:
    """Partial matches a distinct prefix; ``independent``: summed over each motif's own prefixes."""
    parts, seen, weight = [], {}, {}
    for m in motifs:
        for k in range(1, len(m) + 1):
            text = Motif("p", m.canonical().edges[:k]).text
            weight[text] = weight.get(text, 0) + 1
            if text not in seen:
                seen[text] = f"w{len(seen)}_"
                parts += chain(Motif("p", m.canonical().edges[:k]), delta, "strict", seen[text])
    if independent:
        terms = " + ".join(f"{weight[t]} * (SELECT count(*) FROM {tag}{len(t.split()) - 1})" for t, tag in seen.items())
        shared = " + ".join(f"(SELECT count(*) FROM {tag}{len(t.split()) - 1})" for t, tag in seen.items())
        return _whole(graph, parts, f"SELECT '{group}' AS group_name, CAST({terms} AS BIGINT) AS independent, CAST({shared} AS BIGINT) AS shared, round(({terms}) / ({shared}), 4) AS ratio")
    ends = [f"SELECT '{group}' AS group_name, '{t}' AS prefix, count(*) AS partials FROM {tag}{len(t.split()) - 1}" for t, tag in seen.items()]
    return _whole(graph, parts, "\nUNION ALL ".join(ends))


def probes(graph: str, group: str, motifs: list[Motif], delta: int) -> str:
    """Candidate edges looked at for each distinct prefix after the first edge."""
    parts, seen = [], {}
    for m in motifs:
        for k in range(2, len(m) + 1):
            p = Motif("p", m.canonical().edges[:k])
            if p.text not in seen:
                seen[p.text] = f"w{len(seen)}_"
                parts += chain(p, delta, "strict", seen[p.text], loose=True)
    ends = [f"SELECT '{group}' AS group_name, '{t}' AS prefix, count(*) AS probes FROM {tag}{len(t.split()) - 1}" for t, tag in seen.items()]
    return _whole(graph, parts, "\nUNION ALL ".join(ends))


def with_edges(graph: str, rest: str) -> str:
    """``rest`` continues a WITH list or is a SELECT over the table edges."""
    return "WITH edges AS MATERIALIZED (" + GRAPHS[graph] + ")" + (", " if rest.lstrip().startswith("(") or " AS (" in rest.split("SELECT")[0] else "\n") + rest
