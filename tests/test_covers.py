"""Tree codes, tree cover, cluster index and compressed chain lists against brute force; groups and combinations."""

import random

import pytest

from treelogic.analysis.minimize import minimize
from treelogic.analysis.satisfy import outputs_always_bound
from treelogic.baselines.joins import local_semijoin
from treelogic.evaluate.engine import evaluate, evaluate_combinations, nested_matches
from treelogic.graph.model import from_rows
from treelogic.index.chains import ChainIndex, ThreeLegIndex
from treelogic.index.covers import ClusterIndex, TreeCode, TreeCover
from treelogic.query.dsl import parse
from treelogic.query.reference import evaluate as reference
from treelogic.query.reference import micro_graph, random_graph


def rows(df):
    return {tuple(r) for r in df.collect()}


def spark_graph(spark, g):
    return from_rows(spark, [(i, a["tag"], a["val"]) for i, (_, a) in g.nodes.items()], list(g.edges))


def agrees(index, g, gg):
    """The index's pairs and set tests against walks on the graph in memory."""
    nodes = gg.nodes["node"].select("node_id")
    assert rows(index.pairs(nodes, nodes)) == {(a, b) for a in g.nodes for b in g.descendants(a)}
    some = gg.nodes["node"].filter("tag = 'b'")
    ids = {i for i, (_, x) in g.nodes.items() if x["tag"] == "b"}
    assert {r[0] for r in index.reaching(nodes, some).collect()} == {v for v in g.nodes if g.descendants(v) & ids}
    assert {r[0] for r in index.reachable(some, nodes).collect()} == {w for v in ids for w in g.descendants(v)}


@pytest.mark.parametrize("seed,density", [(0, 0.08), (5, 0.22)])
def test_covers_of_any_digraph(spark, seed, density):
    g = random_graph(10, density, "abc", random.Random(seed))
    gg = spark_graph(spark, g)
    nodes, edges = gg.nodes["node"].select("node_id"), gg.all_edges()
    agrees(TreeCover.build(nodes, edges), g, gg)
    chain = ChainIndex.build(nodes, edges)
    legs = ThreeLegIndex.of(chain)
    agrees(legs, g, gg)
    some = gg.nodes["node"].filter("tag = 'a'")
    assert rows(legs.pred_contour(some)) == rows(chain.pred_contour(some))
    assert rows(legs.succ_contour(some)) == rows(chain.succ_contour(some))
    one = next(iter(g.nodes))
    assert rows(legs.successors(one)) == rows(chain.successors(one)) and rows(legs.predecessors(one)) == rows(chain.predecessors(one))


def test_covers_of_the_worked_graph(spark, tmp_path):
    g = micro_graph()
    gg = spark_graph(spark, g)
    nodes = gg.nodes["node"].select("node_id")
    cover = TreeCover.build(nodes, gg.all_edges(), acyclic=True)
    agrees(cover, g, gg)
    assert cover.stats()["nodes"] == len(g.nodes)
    cluster = ClusterIndex.build(gg.nodes["node"].selectExpr("node_id", "tag as label"), gg.all_edges())
    cluster.save(str(tmp_path / "c"))
    again = ClusterIndex.load(spark, str(tmp_path / "c"))
    agrees(again, g, gg)
    tag = {i: x["tag"] for i, (_, x) in g.nodes.items()}
    want = {}
    for a in g.nodes:
        for b in g.descendants(a):
            want[tag[a], tag[b]] = want.get((tag[a], tag[b]), 0) + 1
    assert {(r[0], r[1]): r[2] for r in again.sizes().collect()} == want
    p = parse("x*[tag = 'a']{//y*[tag = 'b'], //z*[tag = 'c']}")
    assert rows(local_semijoin(gg, p, ClusterIndex.build(gg.nodes["node"].selectExpr("node_id", "'node' as label"), gg.all_edges()))[0].select("x", "y", "z")) == rows(evaluate(gg, p).df.select("x", "y", "z"))


def test_tree_codes(spark):
    r = random.Random(3)
    parent = {i: r.randrange(i) for i in range(1, 40)}
    gg = from_rows(spark, [(i, "ab"[i % 2], i) for i in range(40)], [(p, c) for c, p in parent.items()])
    nodes = gg.nodes["node"].select("node_id")

    def above(i):
        out = []
        while i in parent:
            i = parent[i]
            out.append(i)
        return out

    index = TreeCode(nodes, gg.all_edges())
    assert {(r.node_id, tuple(r.code)) for r in index.codes.collect()} == {(i, (*above(i)[::-1], i)) for i in range(40)}
    assert rows(index.pairs(nodes, nodes)) == {(a, i) for i in range(40) for a in above(i)}
    some = gg.nodes["node"].filter("val >= 35")
    assert {r[0] for r in index.reaching(nodes, some).collect()} == {a for i in range(35, 40) for a in above(i)}
    assert {r[0] for r in index.reachable(some, nodes).collect()} == {i for i in range(40) if set(above(i)) & set(range(35, 40))}
    empty = nodes.limit(0)
    assert TreeCode(empty, gg.all_edges().limit(0)).pairs(nodes, nodes).count() == 0
    with pytest.raises(Exception, match="two parents"):
        TreeCode(nodes, from_rows(spark, [(0, "a", 0)], [(0, 2), (1, 2)]).all_edges())


def test_bound_outputs():
    p = parse("r*{//x![tag = 'a'], //y![tag = 'b'], //z[tag = 'c']} where x or y")
    assert outputs_always_bound(p) and outputs_always_bound(p, ["z"])
    assert not outputs_always_bound(p, ["x"]) and not outputs_always_bound(p, ["y"])
    assert outputs_always_bound(parse("r*{//x![tag = 'a'], //y![tag = 'b']} where x and (x or y)"), ["x"])


def test_optional_nodes_force_nothing():
    p = parse("r*{//n[tag = 'a'], //m?*[tag = 'a']}")
    assert "n" in minimize(p)[0].nodes


def test_combinations_and_nested_groups(spark):
    g = micro_graph()
    gg = spark_graph(spark, g)
    p = parse("x*[tag = 'a']{//y![tag = 'b'], //z![tag = 'c']} where y or z")
    found = rows(evaluate_combinations(gg, p, ["y", "z"]).selectExpr("x", "y", "z", "concat_ws(',', present)"))
    tag = {i: x["tag"] for i, (_, x) in g.nodes.items()}
    want = set()
    for x in (i for i in tag if tag[i] == "a"):
        ys, zs = ([d for d in g.descendants(x) if tag[d] == t] for t in "bc")
        if ys or zs:
            want |= {(x, y, z, ",".join(n for n, v in (("y", y), ("z", z)) if v is not None)) for y in ys or [None] for z in zs or [None]}
    assert found == want and want
    with pytest.raises(ValueError):
        evaluate_combinations(gg, p, ["x"])
    q = parse("x*[tag = 'a']{//y*[tag = 'b']{//z*}}")
    flat = {tuple(t[n] for n in "xyz") for t in (dict(zip(q.outputs(), r)) for r in reference(g, q))} if q.outputs() == ["x", "y", "z"] else None
    nested = nested_matches(gg, q, ["x", "y"])
    assert nested.columns == ["x", "x_matches"]
    assert {(r.x, m.y, k.z) for r in nested.collect() for m in r.x_matches for k in m.y_matches} == flat
    assert nested.count() == len({f[0] for f in flat})
    with pytest.raises(ValueError):
        nested_matches(gg, q, ["z"])
