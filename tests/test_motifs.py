"""Motifs, trees, plans: expectations written by hand."""

import pytest

from motifspark.catalog import GROUPS, MOTIFS, group
from motifspark.heuristic import advise
from motifspark.motif import Motif
from motifspark.plan import step
from motifspark.tree import PrefixTree, similarity_by_prefix
from motifspark.workloads import TREES


def test_parse_and_relabel():
    assert Motif.parse("m", "X>Y, Y>Z").canonical().edges == ((0, 1), (1, 2))
    assert Motif.parse("m", "BC CA AB").text == "AB BC CA"
    assert MOTIFS["lollipop"].edge_at(3) == (3, 1, None)
    for bad in ("", "A", "ABC"):
        with pytest.raises(ValueError):
            Motif.parse("m", bad)
    with pytest.raises(ValueError):
        Motif("m", ((0, 1),), (None, None))


def test_odd_cycles():
    odd = {"tri_cycle", "tri_ff", "lollipop", "lollipop_ret"}
    assert {n for n, m in MOTIFS.items() if not m.is_odd_cycle_free()} == odd


@pytest.mark.parametrize("key", TREES)
def test_trees(key):
    name, rows = TREES[key]
    assert sorted(PrefixTree.build(group(name)).rows(), key=str) == sorted(rows, key=str)


def test_tree_rule():
    """A prefix stands in the tree iff it is a query, several edges follow it, or it is the root."""
    for ms in [*map(group, GROUPS), list(MOTIFS.values())]:
        t = PrefixTree.build(ms)
        keys = [m.canonical().keys() for m in ms]
        follow = {}
        for k in keys:
            for i in range(len(k)):
                follow.setdefault(k[:i], set()).add(k[i])
        want = set(keys) | {p for p, f in follow.items() if len(f) > 1 and p} | {t.root.pattern}
        assert {n.pattern for n, _ in t.nodes()} == want
        assert all(p is None or n.pattern[: len(p.pattern)] == p.pattern for n, p in t.nodes())
        assert t.similarity() == pytest.approx(similarity_by_prefix(ms))


def test_subset_tree_is_the_subtree():
    whole, part = PrefixTree.build(group("walkthrough")), PrefixTree.build([MOTIFS["lollipop"], MOTIFS["quad_cycle"]])
    assert whole.root.children[1] == part.root


def test_aliases_and_single():
    t = PrefixTree.build([Motif.parse("one", "XY YZ"), MOTIFS["path2"], MOTIFS["path3"]])
    assert t.aliases == {"path2": "one"} and t.queries == ["one", "path2", "path3"]
    with pytest.raises(ValueError):
        PrefixTree.build([Motif.parse("one", "XY YZ"), MOTIFS["path2"]], dedupe=False)
    with pytest.raises(ValueError):
        PrefixTree.build([])
    assert PrefixTree.build([MOTIFS["tri_cycle"]]).similarity() == 0
    assert PrefixTree.build(group("C3")).render().splitlines()[0] == "AB [-]"


def test_predicates_part_the_tree():
    a, b = MOTIFS["tri_cycle"], MOTIFS["tri_ff"].with_predicate(0, "weight > 1")
    assert PrefixTree.build([a, b]).root.pattern == ()
    c = MOTIFS["path2"].with_label(1, "it's")
    assert c.where == ("dlabel = 'it''s'", None)


def test_pruning():
    t = PrefixTree.build(group("C3")).prune_bipartite()
    assert {n.query for n, _ in t.nodes()} == {None, "pingpong3", "scatter_gather", "path3", "quad_cycle"}
    assert len(t.queries) == 8


def test_steps():
    kinds = lambda text: [step(Motif.parse("m", text).keys()[:k]).kind for k in range(1, len(text.split()) + 1)]
    assert kinds("AB BC CD DB BA") == ["root", "out", "out", "closed", "closed"]
    assert kinds("AB CB DB") == ["root", "in", "in"]
    assert kinds("AA AB BB CD") == ["root", "out", "loop", "free"]
    assert kinds("AB CC") == ["root", "loop"]


def test_advice():
    assert advise(True, 0.1, "constrained").co_mine
    assert not advise(False, 0.43, "constrained").co_mine and advise(False, 0.44, "constrained").co_mine
    assert advise(False, 0.1, "plenty").prefer_smaller_delta
