"""Constants and components, merged tests, columns of untyped outputs, counts with repeated rows."""

import random

import pytest

from tests.test_analysis import random_pattern
from tests.test_engine import rows, spark_graph
from treelogic.analysis.contain import contained, homomorphism
from treelogic.evaluate.engine import Options, Pipeline, count_matches, evaluate, evaluate_multi, evaluate_present
from treelogic.graph.model import EdgeSet, PropertyGraph, global_id
from treelogic.index.chains import ChainIndex
from treelogic.index.reach import Closure
from treelogic.query.dsl import parse
from treelogic.query.reference import evaluate as reference
from treelogic.query.reference import micro_graph, random_graph


@pytest.fixture(scope="module")
def micro(spark):
    g = micro_graph()
    gg = spark_graph(spark, g)
    return g, gg, ChainIndex.build(gg.nodes["node"], gg.all_edges()), Closure(gg.all_edges())


@pytest.mark.parametrize("text", [
    "b*[tag = 'b']{//c*[tag = 'c'], //d*[tag = 'd'], //e*[tag = 'e']}",
    "b*[tag = 'b']{//c[tag = 'c']{//e*[tag = 'e']}, //d*[tag = 'd']}",
    "a[tag = 'a']{//b*[tag = 'b'], //e*[tag = 'e']}",
    "a*[tag = 'a']{//b[tag = 'b']{//d*[tag = 'd']}, //c*}",
])
def test_trimming_and_merged_tests(micro, text):
    g, gg, chain, closure = micro
    p = parse(text)
    want = reference(g, p)
    for options in ({"index": chain}, {"index": chain, "trim": True}, {"index": chain, "trim": False}, {"index": closure, "trim": True}, {"index": chain, "trim": True, "lean": False}):
        assert rows(evaluate(gg, p, **options).df) == want, options


def test_random_patterns_trimmed(spark):
    r = random.Random(77)
    for _ in range(5):
        g = random_graph(6, 0.4, "abc", r)
        p = random_pattern(r)
        gg = spark_graph(spark, g)
        assert rows(evaluate(gg, p, index=Closure(gg.all_edges()), trim=True).df) == reference(g, p), str(p)


def test_multi_and_present(micro):
    g, gg, chain, _ = micro
    p = parse("b*[tag = 'b']{//c![tag = 'c'], //d*[tag = 'd'], //e*[tag = 'e']}")
    found = evaluate_multi(gg, p, {"b": ["b"], "be": ["b", "e"], "de": ["d", "e"]}, index=chain)
    for name, df in found.items():
        assert rows(df) == reference(g, p.with_outputs(df.columns)), name
    q = parse("b*[tag = 'b']{//c![tag = 'c'], //d![tag = 'd']} where c or d")
    shown = rows(evaluate_present(gg, q, index=chain))
    below = {b: {g.nodes[x][1]["tag"] for x in g.descendants(b)} for b, (_, a) in g.nodes.items() if a["tag"] == "b"}
    assert shown == {(b, "c" in t, "d" in t) for b, t in below.items() if {"c", "d"} & t}


def test_untyped_outputs_have_all_kinds(spark):
    a = spark.createDataFrame([(1, "x")], "node_id long, name string")
    b = spark.createDataFrame([(2, "t"), (3, "u")], "node_id long, tag string")
    edges = spark.createDataFrame([(1, 2), (1, 3)], "src long, dst long")
    g = PropertyGraph({"a": a, "b": b}, [EdgeSet("ab", "a", "b", "ref", edges)])
    p = parse("x:a*{/y*}")
    assert len(rows(evaluate(g, p).df)) == 2
    assert rows(evaluate(g, p, project={"y": ["tag"]}).df) == {("t",), ("u",)}
    assert rows(evaluate(g, parse("y*"), project={"y": ["name", "tag"]}).df) == {("x", None), (None, "t"), (None, "u")}


def test_counts_with_repeated_rows(spark):
    nodes = spark.createDataFrame([(1, "a"), (1, "a"), (2, "b"), (2, "b"), (3, "b")], "node_id long, tag string")
    g = PropertyGraph({"node": nodes}, [EdgeSet("e", "node", "node", "ref", spark.createDataFrame([(1, 2), (1, 3)], "src long, dst long"))])
    p = parse("x*[tag = 'a']{/y*[tag = 'b']}")
    assert count_matches(g, p) == 2 == evaluate(g, p).df.count()


def test_outputs_of_containment_in_order():
    p = parse("r{//x*[tag = 'a'], //y*[tag = 'b']}")
    q = parse("r{//x*[tag = 'b'], //y*[tag = 'a']}")
    assert not contained(p, q) and contained(p, p)
    assert contained(p, q, ordered=False) and homomorphism(q, p, ordered=False)["x"] == "y"


def test_ids_that_do_not_fit(spark):
    df = spark.createDataFrame([(-1,)], "k long")
    with pytest.raises(Exception, match="does not fit"):
        df.select(global_id(3, df["k"])).collect()


def test_pair_test_and_pointers(micro):
    g, gg, chain, _ = micro
    every = [(a, b) for a in g.nodes for b in g.nodes]
    found = chain.reaches(gg.spark.createDataFrame(every, "src long, dst long"))
    assert {(r["src"], r["dst"]): r["reaches"] for r in found.collect()} == {(a, b): b in g.descendants(a) for a, b in every}
    full = {(r["cid"], r["sid"]) for r in chain.entries.collect()}
    for r in chain.trace_pointers().collect():
        ahead = [s for c, s in full if c == r["cid"] and s >= r["sid"]]
        assert r["next_sid"] == min(ahead, default=None)


def test_naive_uses_no_round(micro, monkeypatch):
    from treelogic.baselines import joins as J

    g, gg, _, closure = micro
    for name in ("prune_down", "prune_up"):
        monkeypatch.setattr(Pipeline, name, lambda *a, **b: 1 / 0)
    for text in ("b*[tag = 'b']{//c![tag = 'c'], //d![tag = 'd'], //e*[tag = 'e']} where d and not c", "b*[tag = 'b']{//c![tag = 'c']{//e![tag = 'e']}} where not (c)", "b*[tag = 'b']{//c![tag = 'c'], //d![tag = 'd']} where c or not d"):
        p = parse(text)
        assert rows(J.naive_evaluate(gg, p, closure)) == reference(g, p)


def test_twig_engines_on_commerce(spark, sf_dir):
    from treelogic.baselines import joins as J
    from treelogic.graph import catalog
    from treelogic.workloads.patterns import auction

    g = catalog.commerce(spark, sf_dir)
    want = rows(evaluate(g, auction(1)).df)
    for method in ("paths", "nested"):
        assert rows(J.decompose_evaluate(g, auction(1), J.twig_engine(method))[0].select("c", "o", "p")) == want
    assert Pipeline(g, auction(2), Options(lean=True)).columns(auction(2).nodes["l"]) == ["@lineitem_part", "@lineitem_supplier", "@orders_lineitem"]
