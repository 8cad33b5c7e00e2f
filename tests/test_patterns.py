import datetime as dt

import pytest

from treelogic.query.dsl import from_path, parse
from treelogic.query.pattern import Atom, PatternNode, TreePattern, node
from treelogic.query.reference import certificates, evaluate, micro_graph


def test_validation():
    for wrong in (
        lambda: TreePattern(node("a", pred=True)),
        lambda: TreePattern(node("a", node("a"))),
        lambda: TreePattern(node("a", node("b", node("c"), pred=True))),
        lambda: TreePattern(node("a", node("b"), where="b")),
        lambda: TreePattern(node("a", PatternNode("b", backbone=False, output=True))),
        lambda: Atom("x", "~", 1),
    ):
        with pytest.raises(ValueError):
            wrong()


def test_fragments_and_extended():
    p = parse("b*{//c!, //d!, //e*} where d and not c")
    assert p.fragment() == "full" and p.size() == 4
    assert str(p.extended("b")) == "e and d and not c"
    assert parse("b*{//c!, //d!}").fragment() == "conjunctive"
    assert parse("b*{//c!, //d!} where c or d").fragment() == "union-conjunctive"
    assert p.polarity("c") == {False} and p.polarity("d") == {True}


def test_text_and_json_round_trip():
    p = parse("o:orders*[o_orderdate >= date '1996-01-01' and x != 'it''s']{/l:lineitem![grp = 1], //c:customer*?[v < 2.5]} where not l")
    assert p.nodes["o"].atoms[0].constant == dt.date(1996, 1, 1) and p.nodes["o"].atoms[1].constant == "it's"
    assert p.nodes["c"].optional and p.nodes["l"].edge == "pc"
    q = parse("b*[tag = 'b']{//c![val > 3]} where not c")
    assert TreePattern.from_json(q.to_json()).to_json() == q.to_json()
    for wrong in ("b*{", "b where", "b{//c!} where d", "1b", "b] "):
        with pytest.raises((ValueError, KeyError)):
            parse(wrong)


@pytest.mark.parametrize("formula, edge, want", [
    ("c and d", "//", {(2, 8), (2, 10), (3, 10), (11, 10)}),
    ("c or d", "//", {(2, 8), (2, 10), (3, 10), (9, 8), (9, 10), (11, 10)}),
    ("d and not c", "//", {(9, 8), (9, 10)}),
    ("c and not d", "//", set()),
    ("c and d", "/", {(2, 8), (2, 10), (3, 10)}),
    ("d and not c", "/", {(9, 8), (9, 10), (11, 10)}),
])
def test_micro_graph(formula, edge, want):
    p = parse(f"b*[tag = 'b']{{{edge}c![tag = 'c'], {edge}d![tag = 'd'], //e*[tag = 'e']}} where {formula}")
    assert evaluate(micro_graph(), p) == want


def test_singleton_parent_and_modes():
    g = micro_graph()
    assert evaluate(g, parse("a[tag = 'a']{//b*[tag = 'b']{//e*[tag = 'e']}}")) == {(2, 8), (2, 10), (3, 10)}
    p = parse("x*[tag = 'e']{//y*[tag = 'e']}")
    assert evaluate(g, p) == {(8, 10)} and evaluate(g, p, reflexive=True) == {(8, 8), (8, 10), (10, 10)}
    truth = certificates(g, parse("b*[tag = 'b']{//c![tag = 'c'], //d![tag = 'd']} where c or d"), {"b": 9})
    assert truth == {"b": {"c": False, "d": True}}


def test_path_import():
    p = from_path("//a[b//c]/d")
    assert p.size() == 4 and p.outputs() == ["n4"] and p.nodes["n2"].edge == "pc" and p.nodes["n3"].edge == "ad"
