import random

import pytest

from tests.test_analysis import random_pattern
from treelogic.baselines import joins as J
from treelogic.baselines import twigs as T
from treelogic.evaluate.engine import count_matches, evaluate, group_matches
from treelogic.graph.model import from_rows
from treelogic.index.chains import ChainIndex, three_leg_cover
from treelogic.index.reach import Closure, Frontier
from treelogic.query.dsl import parse
from treelogic.query.reference import evaluate as reference
from treelogic.query.reference import micro_graph, random_graph


def rows(df):
    return {tuple(r) for r in df.collect()}


def spark_graph(spark, g):
    return from_rows(spark, [(i, a["tag"], a["val"]) for i, (_, a) in g.nodes.items()], list(g.edges))


@pytest.fixture(scope="module")
def micro(spark):
    g = micro_graph()
    gg = spark_graph(spark, g)
    return g, gg, ChainIndex.build(gg.nodes["node"], gg.all_edges()), Closure(gg.all_edges())


def test_indexes_agree(micro):
    g, gg, chain, closure = micro
    nodes = gg.nodes["node"].select("node_id")
    want = {(a, b) for a in g.nodes for b in g.descendants(a)}
    assert rows(closure.table) == want == rows(chain.pairs(nodes, nodes)) == rows(Frontier(gg.all_edges()).pairs(nodes, nodes))
    for tag in "bce":
        some = gg.nodes["node"].filter(f"tag = '{tag}'")
        ids = {i for i, (_, x) in g.nodes.items() if x["tag"] == tag}
        up, down = {v for v in g.nodes if g.descendants(v) & ids}, {w for v in ids for w in g.descendants(v)}
        for index in (chain, Frontier(gg.all_edges())):
            assert {r[0] for r in index.reaching(nodes, some).collect()} == up
            assert {r[0] for r in index.reachable(some, nodes).collect()} == down
    stats = chain.stats()
    assert stats["nodes"] == 11 and chain.pred_contour(gg.nodes["node"]).count() <= stats["chains"]
    kept, gone = three_leg_cover(chain.entries)
    assert kept.count() + gone.count() == chain.entries.count()


def test_cyclic_graph(spark):
    r = random.Random(5)
    g = random_graph(9, 0.22, "abc", r)
    gg = spark_graph(spark, g)
    nodes = gg.nodes["node"].select("node_id")
    assert rows(ChainIndex.build(nodes, gg.all_edges()).pairs(nodes, nodes)) == {(a, b) for a in g.nodes for b in g.descendants(a)}


@pytest.mark.parametrize("formula", ["c and d", "c or d", "d and not c"])
def test_options_agree(micro, formula):
    g, gg, chain, closure = micro
    p = parse(f"b*[tag = 'b']{{//c![tag = 'c'], /d![tag = 'd'], //e*[tag = 'e']}} where {formula}")
    want = reference(g, p)
    for options in ({"index": chain}, {"index": closure, "shrink": False}, {"index": closure, "prune_up": False}, {"index": closure, "minimize": True}):
        assert rows(evaluate(gg, p, **options).df) == want


def test_relaxed_children_and_count(micro):
    g, gg, _, closure = micro
    p = parse("a*[tag = 'a']{/b*[tag = 'b']{/x*{/y*}}}")
    want = reference(g, p)
    assert want and rows(evaluate(gg, p, index=closure, pc_mode="relax").df) == want
    assert count_matches(gg, p, index=closure) == len(want)
    grouped = {r[0]: {tuple(m) for m in r[1]} for r in group_matches(gg, parse("b*[tag = 'b']{//e*[tag = 'e']}"), "b", index=closure).collect()}
    assert grouped == {2: {(8,), (10,)}, 3: {(10,)}, 9: {(8,), (10,)}, 11: {(10,)}}


def test_random_patterns_against_reference(spark):
    r = random.Random(23)
    done = 0
    while done < 8:
        g = random_graph(7, 0.35, "abc", r)
        p = random_pattern(r)
        want = reference(g, p)
        if not want and done % 2:
            continue
        gg = spark_graph(spark, g)
        closure = Closure(gg.all_edges())
        assert rows(evaluate(gg, p, index=closure).df) == want, str(p)
        done += 1


def test_baselines_agree(micro):
    g, gg, _, closure = micro
    p = parse("b*[tag = 'b']{//d*[tag = 'd'], //e*[tag = 'e']}")
    want = reference(g, p)
    assert rows(J.naive_evaluate(gg, p, closure)) == want
    assert rows(J.hash_structural(gg, p, index=closure)[0]) == want
    best, info = J.hash_structural(gg, p, plans="all", index=closure)
    assert rows(best) == want and info["plans"] == 2
    assert rows(J.hash_structural(gg, p, represent="graph", index=closure)[0]) == want
    assert rows(J.local_semijoin(gg, p, closure)[0]) == want
    assert rows(T.pool_twig(gg, p)[0]) == want
    q = parse("b*[tag = 'b']{//c![tag = 'c'], //d![tag = 'd']} where d and not c")
    engine = lambda graph, pattern: evaluate(graph, pattern, index=closure).df
    assert rows(J.dnf_evaluate(gg, q, engine)) == reference(g, q) == rows(J.operator_twig(gg, q))
