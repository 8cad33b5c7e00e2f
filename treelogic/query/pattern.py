"""Logic tree patterns: a tree of nodes with attribute predicates and formulas.

A node is *backbone* (it has an image in every match) or *predicate* (it only
takes part in its parent's formula).  Backbone nodes hang under backbone nodes
only; predicate nodes anywhere.  An edge is parent-child (``pc``) or
ancestor-descendant (``ad``, a nonempty path).  Outputs are backbone nodes.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from typing import Any

from treelogic.query.logic import TRUE, And, Formula, Var, monotone, parse_formula, simplify

OPERATIONS = ("<", "<=", "=", "!=", ">", ">=")


@dataclass(frozen=True)
class Atom:
    """``attribute operation constant``; false where the attribute is missing."""

    attribute: str
    operation: str
    constant: Any

    def __post_init__(self):
        if self.operation not in OPERATIONS:
            raise ValueError(f"no such comparison: {self.operation}")

    def holds(self, value: Any) -> bool:
        if value is None:
            return False
        c = self.constant
        return {"<": lambda: value < c, "<=": lambda: value <= c, "=": lambda: value == c, "!=": lambda: value != c, ">": lambda: value > c, ">=": lambda: value >= c}[self.operation]()

    def __str__(self):
        return f"{self.attribute} {self.operation} {json.dumps(self.constant, default=str)}"


@dataclass(frozen=True)
class PatternNode:
    """A pattern node; ``kind`` restricts it to one node table (None: any)."""

    name: str
    atoms: tuple[Atom, ...] = ()
    kind: str | None = None
    backbone: bool = True
    output: bool = False
    edge: str = "ad"
    optional: bool = False
    formula: Formula = TRUE
    children: tuple[PatternNode, ...] = field(default=())

    def walk(self) -> Iterator[PatternNode]:
        """This node and all below, parents first."""
        yield self
        for c in self.children:
            yield from c.walk()

    def holds(self, kind: str | None, attributes: dict[str, Any]) -> bool:
        """Whether a data node passes the kind and attribute tests."""
        return (self.kind is None or self.kind == kind) and all(a.holds(attributes.get(a.attribute)) for a in self.atoms)


class TreePattern:
    """A validated pattern."""

    def __init__(self, root: PatternNode):
        self.root = root
        self.nodes = {n.name: n for n in root.walk()}
        self.parent: dict[str, str | None] = {root.name: None}
        for n in root.walk():
            for c in n.children:
                self.parent[c.name] = n.name
        self.validate()

    def validate(self) -> None:
        every = list(self.root.walk())
        if len(self.nodes) != len(every):
            raise ValueError("node names repeat")
        if not self.root.backbone:
            raise ValueError("the root is a backbone node")
        for n in every:
            if n.edge not in ("pc", "ad"):
                raise ValueError(f"{n.name}: no such edge {n.edge}")
            if n.output and not n.backbone:
                raise ValueError(f"{n.name}: outputs are backbone nodes")
            if n.optional and (not n.backbone or n.name == self.root.name):
                raise ValueError(f"{n.name}: optional edges lead to backbone nodes")
            predicates = {c.name for c in n.children if not c.backbone}
            if not n.backbone and len(predicates) < len(n.children):
                raise ValueError(f"{n.name}: backbone nodes hang under backbone nodes only")
            if unknown := n.formula.variables() - predicates:
                raise ValueError(f"{n.name}: the formula names {sorted(unknown)}, which are no predicate children")

    # structure

    def children(self, name: str, backbone: bool | None = None) -> list[PatternNode]:
        return [c for c in self.nodes[name].children if backbone is None or c.backbone == backbone]

    def postorder(self) -> list[PatternNode]:
        return list(reversed(list(self.root.walk())))

    def outputs(self) -> list[str]:
        return [n.name for n in self.root.walk() if n.output]

    def backbone(self) -> list[str]:
        return [n.name for n in self.root.walk() if n.backbone]

    def path(self, name: str) -> list[str]:
        """Names from the root down to the node."""
        out = [name]
        while self.parent[out[-1]] is not None:
            out.append(self.parent[out[-1]])
        return out[::-1]

    def size(self) -> int:
        return len(self.nodes)

    def fragment(self) -> str:
        """``conjunctive`` (only AND), ``union-conjunctive`` (no negation) or ``full``."""
        formulas = [simplify(n.formula) for n in self.root.walk()]
        if not all(map(monotone, formulas)):
            return "full"
        plain = all(isinstance(f, Var) or f == TRUE or isinstance(f, And) and all(isinstance(i, Var) for i in f.items) for f in formulas)
        used = all(n.formula.variables() == {c.name for c in n.children if not c.backbone} for n in self.root.walk())
        return "conjunctive" if plain and used else "union-conjunctive"

    def extended(self, name: str) -> Formula:
        """The node's formula and all its backbone children (optional ones do not bind)."""
        n = self.nodes[name]
        return simplify(And((*(Var(c.name) for c in n.children if c.backbone and not c.optional), n.formula)))

    def polarity(self, name: str) -> set[bool]:
        """Signs under which the node's truth is asked for by its ancestors' formulas."""
        from treelogic.query.logic import Not

        def signs(f: Formula, v: str, sign: bool = True) -> set[bool]:
            if isinstance(f, Var):
                return {sign} if f.name == v else set()
            if isinstance(f, Not):
                return signs(f.inner, v, not sign)
            return set().union(*[signs(p, v, sign) for p in f.parts()], set())

        out = {True}
        up = self.path(name)
        for parent, child in zip(up, up[1:]):
            got = signs(self.extended(parent), child) or {True}
            out = {a == b for a in out for b in got}
        return out

    # change

    def map(self, change) -> TreePattern:
        """The pattern whose nodes are ``change(node with changed children)``; None drops a subtree."""
        def go(n: PatternNode) -> PatternNode | None:
            kept = tuple(c for c in (go(c) for c in n.children) if c is not None)
            return change(replace(n, children=kept))

        root = go(self.root)
        if root is None:
            raise ValueError("the root was dropped")
        return TreePattern(root)

    def with_outputs(self, names) -> TreePattern:
        names = set(names)
        return self.map(lambda n: replace(n, output=n.name in names))

    # text forms

    def to_json(self) -> str:
        def go(n: PatternNode) -> dict:
            return {"name": n.name, "kind": n.kind, "pred": [[a.attribute, a.operation, a.constant] for a in n.atoms], "role": "backbone" if n.backbone else "predicate", "output": n.output, "edge": n.edge, "optional": n.optional, "formula": str(n.formula), "children": [go(c) for c in n.children]}

        return json.dumps({"root": go(self.root)}, default=str)

    @classmethod
    def from_json(cls, text: str) -> TreePattern:
        def go(d: dict) -> PatternNode:
            return PatternNode(d["name"], tuple(Atom(a, o, c) for a, o, c in d.get("pred", [])), d.get("kind"), d.get("role", "backbone") == "backbone", bool(d.get("output")), d.get("edge", "ad"), bool(d.get("optional")), parse_formula(d.get("formula") or "true"), tuple(map(go, d.get("children", []))))

        return cls(go(json.loads(text)["root"]))

    def __str__(self):
        def go(n: PatternNode, depth: int) -> list[str]:
            mark = {"pc": "/", "ad": "//"}[n.edge] if depth else ""
            tests = f"[{' and '.join(map(str, n.atoms))}]" if n.atoms else ""
            line = "  " * depth + mark + n.name + (f":{n.kind}" if n.kind else "") + ("*" if n.output else "") + ("?" if n.optional else "") + ("" if n.backbone else " (predicate)") + tests + (f" where {n.formula}" if n.formula != TRUE else "")
            return [line, *[x for c in n.children for x in go(c, depth + 1)]]

        return "\n".join(go(self.root, 0))


def node(name: str, *children: PatternNode, kind: str | None = None, where: str | Formula = TRUE, out: bool = False, edge: str = "ad", pred: bool = False, optional: bool = False, **equal: Any) -> PatternNode:
    """Short form: ``node("a", node("b", pred=True), where="b", tag="x")``."""
    atoms = tuple(Atom(k, "=", v) for k, v in equal.items())
    return PatternNode(name, atoms, kind, not pred, out, edge, optional, parse_formula(where) if isinstance(where, str) else where, children)
