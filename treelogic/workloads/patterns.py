"""The experiment workloads as patterns: auctions, the order trio, random patterns."""

from __future__ import annotations

import datetime as dt
import random

from pyspark.sql import functions as F

from treelogic.graph.model import KEY_BITS, PropertyGraph
from treelogic.query.logic import parse_formula
from treelogic.query.pattern import Atom, PatternNode, TreePattern, node

AUCTION_KEYS = {"c": "c_custkey", "o": "o_orderkey", "p": "p_partkey", "s": "s_suppkey", "p2": "p_partkey"}


def auction(shape: int = 1, a: int = 3, b: int = 7) -> TreePattern:
    """Customers of group a, their orders, the lines and parts of group b (1); with the line's supplier
    of group a (2); with another line of the order for a part of group b + 1 (3).  All nodes but the
    lines are outputs."""
    line = [node("p", kind="part", out=True, grp=b)]
    if shape >= 2:
        line.append(node("s", kind="supplier", out=True, grp=a))
    lines = [node("l", *line, kind="lineitem")]
    if shape >= 3:
        lines.append(node("l2", node("p2", kind="part", out=True, grp=(b + 1) % 10), kind="lineitem"))
    return TreePattern(node("c", node("o", *lines, kind="orders", out=True), kind="customer", out=True, grp=a))


def auction_draws(n: int = 10) -> list[tuple[int, int]]:
    """Label draws (a, b): b is a + 4, modulo 10."""
    return [(a % 10, (a + 4) % 10) for a in range(n)]


TRIO = {"and": "l1 and l2", "or": "l1 or l2", "andnot": "l1 and not l2"}


def trio(kind: str = "andnot", edge: str = "ad", formula: str | None = None) -> TreePattern:
    """Orders of 1996 to 1998 by whether they have lines of supplier groups 1 and 2."""
    lines = [PatternNode(f"l{i}", (Atom("grp", "=", i),), "lineitem", False, False, edge) for i in (1, 2)]
    years = (Atom("o_orderdate", ">=", dt.datetime(1996, 1, 1)), Atom("o_orderdate", "<", dt.datetime(1999, 1, 1)))
    return TreePattern(PatternNode("o", years, "orders", True, True, "ad", False, parse_formula(formula or TRIO[kind]), tuple(lines)))


def random_patterns(graph: PropertyGraph, size: int, n: int, seed: int = 42, pc_share: float = 0.3, kind: str = "event", label: str = "label", sample: int = 60_000) -> list[TreePattern]:
    """Random trees with labels drawn by walking the graph from sampled nodes, so each has a match.

    The walk needs the graph at hand: the edges among a bounded number of nodes
    (``sample``, by id) are brought to the driver.  All nodes are outputs.
    """
    labels = {r[0]: r[1] for r in graph.nodes[kind].select("node_id", label).orderBy("node_id").limit(sample).collect()}
    top = max(labels, default=0)
    follow: dict[int, list[int]] = {}
    for e in graph.between(kind, kind):
        for src, dst in e.df.filter((F.col("src") <= top) & (F.col("dst") <= top)).collect():
            follow.setdefault(src, []).append(dst)
    for v in follow.values():
        v.sort()
    r = random.Random(seed)
    starts = sorted(follow)
    out: list[TreePattern] = []
    while len(out) < n and starts:
        image = {"n0": r.choice(starts)}
        edges: dict[str, tuple[str, str]] = {}
        tries = 0
        while len(image) < size and tries < 50:
            tries += 1
            up = r.choice(sorted(image))
            v = image[up]
            if v not in follow:
                continue
            direct = r.random() < pc_share
            w = r.choice(follow[v])
            for _ in range(0 if direct else r.randint(0, 3)):
                if w in follow:
                    w = r.choice(follow[w])
            name = f"n{len(image)}"
            image[name] = w
            edges[name] = (up, "pc" if direct else "ad")
        if len(image) < size:
            continue

        def build(name: str, edge: str = "ad") -> PatternNode:
            kids = tuple(build(k, e) for k, (up, e) in edges.items() if up == name)
            return PatternNode(name, (Atom(label, "=", labels[image[name]]),), kind, True, True, edge, False, parse_formula("true"), kids)

        out.append(TreePattern(build("n0")))
    return out


def natural(column: str) -> F.Column:
    """The natural key inside a node id."""
    return F.col(column).bitwiseAND(F.lit((1 << KEY_BITS) - 1))
