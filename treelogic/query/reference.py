"""The semantics by brute force, for small graphs: tests compare everything with this."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import product
from typing import Any

from treelogic.query.pattern import TreePattern


@dataclass
class SmallGraph:
    """Node -> (kind, attributes), and edges."""

    nodes: dict[int, tuple[str | None, dict[str, Any]]]
    edges: set[tuple[int, int]]
    _next: dict[int, set[int]] = field(default_factory=dict)

    def __post_init__(self):
        self._next = {v: set() for v in self.nodes}
        for a, b in self.edges:
            self._next[a].add(b)

    def children(self, v: int) -> set[int]:
        return self._next[v]

    def descendants(self, v: int) -> frozenset[int]:
        """All nodes at the end of a nonempty path from v."""
        seen: set[int] = set()
        todo = list(self._next[v])
        while todo:
            w = todo.pop()
            if w not in seen:
                seen.add(w)
                todo += self._next[w]
        return frozenset(seen)


def down_matches(g: SmallGraph, p: TreePattern, reflexive: bool = False) -> dict[str, set[int]]:
    """For each pattern node, the data nodes that satisfy the whole sub-pattern below it."""
    reach = {v: g.descendants(v) | ({v} if reflexive else set()) for v in g.nodes}
    out: dict[str, set[int]] = {}
    for u in p.postorder():
        formula = p.extended(u.name)
        good = set()
        for v, (kind, attributes) in g.nodes.items():
            if u.holds(kind, attributes):
                truth = {c.name: bool((g.children(v) if c.edge == "pc" else reach[v]) & out[c.name]) for c in u.children}
                if formula.value(truth):
                    good.add(v)
        out[u.name] = good
    return out


def evaluate(g: SmallGraph, p: TreePattern, reflexive: bool = False) -> set[tuple]:
    """The set of output tuples, in the order of ``p.outputs()``; None for an optional node without match."""
    down = down_matches(g, p, reflexive)
    names = p.outputs()

    @lru_cache(maxsize=None)
    def below(name: str, v: int) -> frozenset[tuple]:
        """Assignments (pairs of output name and node) of the backbone below u with u at v."""
        branches = []
        for c in p.children(name, backbone=True):
            near = g.children(v) if c.edge == "pc" else g.descendants(v) | ({v} if reflexive else set())
            found = frozenset(row for w in near & down[c.name] for row in below(c.name, w))
            if not found and c.optional:
                found = frozenset({tuple((n.name, None) for n in c.walk() if n.output)})
            branches.append(found)
        own = ((name, v),) if p.nodes[name].output else ()
        return frozenset(own + tuple(x for part in choice for x in part) for choice in product(*branches))

    return {tuple(dict(row)[n] for n in names) for v in down[p.root.name] for row in below(p.root.name, v)}


def certificates(g: SmallGraph, p: TreePattern, match: dict[str, int]) -> dict[str, dict[str, bool]]:
    """Truth of every predicate child at each backbone node of a match."""
    down = down_matches(g, p)
    return {u: {c.name: bool((g.children(v) if c.edge == "pc" else g.descendants(v)) & down[c.name]) for c in p.nodes[u].children if not c.backbone} for u, v in match.items()}


def micro_graph() -> SmallGraph:
    """The hand-made graph of the test fixtures: 11 nodes (tag, val), 13 edges."""
    tags = "1 a1, 2 b5, 3 b7, 4 c1, 5 d2, 6 c3, 7 d9, 8 e1, 9 b5, 10 e2, 11 b4"
    nodes = {int(i): (None, {"tag": x[0], "val": int(x[1:])}) for i, x in (item.split() for item in tags.split(", "))}
    return SmallGraph(nodes, {(1, 2), (1, 3), (2, 4), (2, 5), (3, 6), (3, 7), (4, 8), (5, 8), (6, 10), (7, 6), (9, 5), (8, 10), (11, 7)})


def random_graph(n: int, p: float, tags: Iterable[str], r, cyclic: bool = True) -> SmallGraph:
    """A seeded random digraph for comparisons."""
    tags = list(tags)
    nodes = {i: (None, {"tag": r.choice(tags), "val": r.randint(0, 9)}) for i in range(1, n + 1)}
    edges = {(a, b) for a in nodes for b in nodes if (a < b or cyclic and (a != b or r.random() < 0.3)) and r.random() < p}
    return SmallGraph(nodes, edges)
