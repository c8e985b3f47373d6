"""One SQL statement for a tree: a common table expression for every prefix."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..plan import bound, step
from ..tree import PrefixTree


def render(tree: PrefixTree, delta: int, ties: str = "strict", table: str = "edges", mode: str = "count") -> str:
    """Spark SQL over a table (edge_id, src, dst, t, tie and attributes)."""
    prefixes, queries = tree.prefixes(), tree.query_of()
    name = {p: f"p{k}" for k, p in enumerate(prefixes)}
    parts = []
    for p in prefixes:
        s, n = step(p), bound(p[:-1])
        where = [f"({s.where})"] if s.where else []
        if len(p) == 1:
            loop = s.u == s.v
            where.append("src = dst" if loop else "src <> dst")
            vs = "src AS v0" if loop else "src AS v0, dst AS v1"
            parts.append(f"{name[p]} AS (SELECT edge_id AS e0, {vs}, t AS t_first, t AS t_last, tie AS tie_last FROM {table} WHERE {' AND '.join(where)})")
            continue
        on = [f"g.{end} = f.v{x}" for end, x in s.anchors]
        on.append("g.t > f.t_last" if ties == "strict" else "(g.t > f.t_last OR g.t = f.t_last AND g.tie > f.tie_last)")
        on.append(f"g.t <= f.t_first + {int(delta)}")
        on += [f"g.{end} <> f.v{k}" for end, _ in s.new for k in range(n)]
        on += ["g.src <> g.dst"] * (len(s.new) == 2) + ["g.src = g.dst"] * (s.kind == "loop")
        source = f"(SELECT * FROM {table} WHERE {s.where})" if s.where else table
        cols = [*(f"f.e{k}" for k in range(len(p) - 1)), f"g.edge_id AS e{len(p) - 1}", *(f"f.v{k}" for k in range(n)), *(f"g.{end} AS v{x}" for end, x in s.new), "f.t_first", "g.t AS t_last", "g.tie AS tie_last"]
        parts.append(f"{name[p]} AS (SELECT {', '.join(cols)} FROM {name[p[:-1]]} f JOIN {source} g ON {' AND '.join(on)})")
    if mode == "count":
        ends = [f"SELECT '{q}' AS motif, count(*) AS n FROM {name[p]}" for p, q in queries.items()]
    else:
        ends = [f"SELECT '{q}' AS motif, concat_ws('-', {', '.join(f'CAST(e{k} AS STRING)' for k in range(len(p)))}) AS edge_path, t_first, t_last FROM {name[p]}" for p, q in queries.items()]
    return "WITH " + ",\n".join(parts) + "\n" + "\nUNION ALL\n".join(ends)


def run(edges: DataFrame, tree: PrefixTree, delta: int, ties: str = "strict", mode: str = "count") -> DataFrame:
    return edges.sparkSession.sql(render(tree, delta, ties, "{edges}", mode), edges=edges)
