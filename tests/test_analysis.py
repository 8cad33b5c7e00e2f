import random

from treelogic.analysis.attributes import attr_sat, entails
from treelogic.analysis.contain import contained, equivalent, isomorphic
from treelogic.analysis.minimize import minimize, operator_twig_size
from treelogic.analysis.satisfy import Analysis, satisfiable, satisfiable_monotone
from treelogic.query.dsl import parse
from treelogic.query.logic import monotone
from treelogic.query.pattern import Atom, TreePattern, node
from treelogic.query.reference import evaluate, random_graph
from treelogic.workloads.registry import worked_patterns


def atoms(*items):
    return tuple(Atom(*i) for i in items)


def test_attributes():
    assert attr_sat(atoms(("a", ">", 1), ("a", "<", 2))) and not attr_sat(atoms(("a", ">", 2), ("a", "<", 2)))
    assert not attr_sat(atoms(("a", "=", 1), ("a", "!=", 1))) and not attr_sat(atoms(("a", "=", 1), ("a", "=", "x")))
    assert entails(atoms(("a", "=", 5)), atoms(("a", "<=", 7)))
    assert not entails(atoms(("a", "=", 5)), atoms(("a", "<=", 7)), "syntactic")
    assert entails(atoms(("a", "<=", 5)), atoms(("a", "<=", 7)), "syntactic")
    assert entails(atoms(("a", ">", 5)), atoms(("a", "!=", 5))) and not entails(atoms(("a", ">", 5)), atoms(("b", ">", 5)))


def test_worked_example():
    p = worked_patterns()
    a = Analysis(p["ad_not"])
    assert {"u5", "u8"} == set(p["ad_not"].nodes) - a.independent
    assert a.subsumed("u2", "u6") and not Analysis(p["pc_not"]).subsumed("u2", "u6")
    assert not satisfiable(p["ad_not"]) and satisfiable(p["pc_not"])
    assert contained(p["pc"], p["chain"]) and contained(p["pc"], p["ad"]) and not contained(p["chain"], p["pc"])
    assert equivalent(p["ad"], p["chain"])
    small, trace = minimize(p["ad"])
    assert isomorphic(small, p["chain"]) and [gone for _, gone in trace] == [["u5"], ["u2"]]
    assert minimize(small)[1] == []


def random_pattern(r, depth=2):
    count = [0]

    def go(depth, pred):
        count[0] += 1
        name = f"v{count[0]}"
        kids = [go(depth - 1, pred or r.random() < 0.6) for _ in range(r.randint(0, 2))] if depth else []
        own = [k.name for k in kids if not k.backbone]
        text = "true"
        if own:
            text = " ".join(("not " if r.random() < 0.35 else "") + v + (r.choice([" and", " or"]) if i < len(own) - 1 else "") for i, v in enumerate(own))
        return node(name, *kids, pred=pred, out=not pred and r.random() < 0.7, edge=r.choice(["ad", "pc"]), where=text, tag=r.choice("abc"))

    p = TreePattern(go(depth, False))
    return p if p.outputs() else p.with_outputs([p.root.name])


def test_analysis_against_brute_force():
    r = random.Random(11)
    patterns = [random_pattern(r, r.choice([1, 2])) for _ in range(120)]
    for p in patterns:
        q, can = minimize(p)[0], satisfiable(p)
        if all(monotone(n.formula) for n in p.root.walk()):
            assert satisfiable_monotone(p) == can
        for _ in range(8):
            g = random_graph(r.randint(2, 7), r.choice([0.2, 0.4]), "abc", r)
            found = evaluate(g, p)
            assert can or not found
            assert evaluate(g, q) == found
    checked = 0
    for _ in range(600):
        p, q = r.choice(patterns), r.choice(patterns)
        if len(p.outputs()) == len(q.outputs()) == 1 and satisfiable(p) and contained(p, q):
            checked += 1
            for _ in range(5):
                g = random_graph(r.randint(2, 7), 0.35, "abc", r)
                assert evaluate(g, p) <= evaluate(g, q)
    assert checked > 20


def test_operator_twigs_are_larger():
    sizes = operator_twig_size(parse("b*{//c!{//x!}, //d!{//y!}, //e!} where (c and d) or (d and e) or (c and e)"))
    assert sizes["operator_twig"] > sizes["pattern"]
