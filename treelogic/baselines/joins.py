"""Join-based baselines: hash structural joins, local semi-joins, all pairs, naive joins, Boolean decompositions."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.evaluate.engine import Options, Pipeline, candidates, evaluate
from treelogic.graph.model import EdgeSet, PropertyGraph
from treelogic.index.covers import ClusterIndex
from treelogic.index.reach import Reach
from treelogic.plans import cut
from treelogic.query.logic import FALSE, TRUE, And, Formula, Not, Var, dnf
from treelogic.query.pattern import PatternNode, TreePattern

Engine = Callable[[PropertyGraph, TreePattern], DataFrame]


def pattern_engine(graph: PropertyGraph, pattern: TreePattern) -> DataFrame:
    return evaluate(graph, pattern).df


# Boolean decompositions

def _as_backbone(n: PatternNode) -> PatternNode:
    return replace(n, backbone=True, children=tuple(map(_as_backbone, n.children)), formula=TRUE)


def conjunctive_terms(pattern: TreePattern) -> list[tuple[TreePattern, list[tuple[str, PatternNode]]]]:
    """The pattern as a union of conjunctive patterns, each with the sub-patterns that must be absent:
    (positive pattern, [(node, forbidden child)]).  Formulas are put into disjunctive normal form, nested
    ones first, so their number multiplies."""
    def expand(n: PatternNode) -> Iterator[tuple[PatternNode, list[tuple[str, PatternNode]]]]:
        """Conjunctive versions of a subtree."""
        fixed = [c for c in n.children if c.backbone]
        by_name = {c.name: c for c in n.children}
        for term in dnf(n.formula):
            wanted = [by_name[v] for v, sign in sorted(term) if sign]
            absent = [by_name[v] for v, sign in sorted(term) if not sign]

            def combine(todo: list[PatternNode]) -> Iterator[tuple[list[PatternNode], list]]:
                if not todo:
                    yield [], []
                    return
                for head, bad in expand(todo[0]):
                    for rest, more in combine(todo[1:]):
                        yield [head, *rest], bad + more

            for kids, bad in combine(fixed + wanted):
                yield replace(n, formula=TRUE, children=tuple(_as_backbone(k) if not k.backbone else k for k in kids)), bad + [(n.name, a) for a in absent]

    return [(TreePattern(root), bad) for root, bad in expand(pattern.root)]


def dnf_evaluate(graph: PropertyGraph, pattern: TreePattern, engine: Engine = pattern_engine) -> DataFrame:
    """Union over the terms; a term's negations are differences: rows of the same term with the
    forbidden child present are taken off by all of the term's nodes."""
    outputs = pattern.outputs()
    parts = []
    for term, absent in conjunctive_terms(pattern):
        holders = list(dict.fromkeys(n for n, _ in absent))
        # the forbidden child is asked for at one node at a time, so that node must be in the rows
        whole = term.with_outputs([*outputs, *holders])
        rows = engine(graph, whole)
        for at, child in absent:
            single = TreePattern(replace(term.nodes[at], children=(child,), formula=Var(child.name), output=True, edge="ad"))
            hit = dnf_evaluate(graph, single, engine) if child.children else engine(graph, TreePattern(replace(single.root, children=(_as_backbone(child),), formula=TRUE)))
            rows = rows.join(hit.select(at).distinct(), at, "left_anti")
        parts.append(rows.select(*outputs))
    return reduce(DataFrame.union, parts).distinct() if parts else graph.spark.createDataFrame([], ", ".join(f"{o} long" for o in outputs))


def operator_twig(graph: PropertyGraph, pattern: TreePattern, engine: Engine = pattern_engine) -> DataFrame:
    """Operator-node twigs: each formula in conjunctive normal form, a clause being a block of
    alternatives; a match of a node is an intersection over clauses of unions over alternatives."""
    from treelogic.query.logic import cnf

    p = Pipeline(graph, pattern, Options())

    def at(name: str) -> DataFrame:
        u = pattern.nodes[name]
        rows = candidates(graph, u)
        kids = {c.name: at(c.name) for c in u.children}
        for c in u.children:
            if c.backbone and not c.optional:
                rows = p.operators[c.name].reaching(rows, kids[c.name])
        for clause in cnf(u.formula):
            options = []
            for v, sign in sorted(clause):
                hit = p.operators[v].reaching(rows, kids[v])
                options.append(hit.select("node_id") if sign else rows.select("node_id").join(hit, "node_id", "left_anti"))
            rows = rows.select("node_id").join(reduce(DataFrame.union, options), "node_id", "left_semi")
        return rows

    keep = {n: at(n) for n in pattern.backbone()}
    return joined(pattern, {(pattern.parent[n], n): p.operators[n].pairs(keep[pattern.parent[n]], keep[n]) for n in pattern.backbone() if pattern.parent[n]}, keep)


# joins of edge relations

def conjunctive(pattern: TreePattern) -> TreePattern:
    """The pattern with its predicate nodes as backbone; only for conjunctive patterns."""
    if pattern.fragment() != "conjunctive":
        raise ValueError("a conjunctive pattern is needed; use dnf_evaluate for others")
    return TreePattern(_as_backbone(pattern.root))


def plain_candidates(graph: PropertyGraph, pattern: TreePattern) -> dict[str, DataFrame]:
    """Ids of the nodes that pass each pattern node's tests: the baselines work on node ids and edge tables only."""
    return {u.name: candidates(graph, u) for u in pattern.root.walk()}


def edge_relations(graph: PropertyGraph, pattern: TreePattern, index: Reach | None = None) -> tuple[dict, dict]:
    """(candidates, pairs of each pattern edge), without any pruning."""
    p = Pipeline(graph, pattern, Options(index=index))
    cand = plain_candidates(graph, pattern)
    return cand, {(pattern.parent[n.name], n.name): p.operators[n.name].pairs(cand[pattern.parent[n.name]], cand[n.name]) for n in pattern.root.walk() if pattern.parent[n.name]}


def joined(pattern: TreePattern, pairs: dict[tuple[str, str], DataFrame], cand: dict[str, DataFrame], order: list[tuple[str, str]] | None = None, hint: str | None = None) -> DataFrame:
    """Joins edge relations in the given order and projects to the outputs."""
    order = order or list(pairs)
    outputs = pattern.outputs()
    if not order:
        return cand[pattern.root.name].select(F.col("node_id").alias(pattern.root.name)).distinct()
    rows = None
    for a, b in order:
        part = pairs[a, b].select(F.col("src").alias(a), F.col("dst").alias(b))
        if rows is None:
            rows = part
        else:
            rows = rows.join(part.hint(hint) if hint else part, [c for c in (a, b) if c in rows.columns])
    return rows.select(*outputs).distinct()


def join_orders(edges: list[tuple[str, str]], most: int = 720) -> list[list[tuple[str, str]]]:
    """All connected left-deep orders of the edges, up to ``most``."""
    out: list[list[tuple[str, str]]] = []

    def go(done: list, seen: set, rest: list) -> None:
        if len(out) >= most:
            return
        if not rest:
            out.append(done)
            return
        for e in rest:
            if not done or seen & set(e):
                go([*done, e], seen | set(e), [x for x in rest if x != e])

    go([], set(), edges)
    return out


def hash_structural(graph: PropertyGraph, pattern: TreePattern, plans: str = "first", represent: str = "tuples", index: Reach | None = None, most: int = 24) -> tuple[DataFrame, dict]:
    """Hash joins of unpruned edge relations.

    ``plans="all"`` runs every left-deep order (up to ``most``) and reports the
    fastest; ``represent="graph"`` keeps the relations as a graph and deletes,
    until nothing changes, edges whose ends lack a needed partner, before the
    tuples are made.
    """
    pattern = conjunctive(pattern)
    cand, pairs = edge_relations(graph, pattern, index)
    if represent == "graph":
        pairs = {k: cut(v) for k, v in pairs.items()}
        sizes = {k: v.count() for k, v in pairs.items()}
        rounds = 0
        while True:
            rounds += 1
            for (a, b), e in list(pairs.items()):
                for (x, y), other in pairs.items():
                    if (x, y) == (a, b):
                        continue
                    if x == b:
                        e = e.join(other.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi")
                    elif y == a:
                        e = e.join(other.select(F.col("dst").alias("src")).distinct(), "src", "left_semi")
                    elif x == a:
                        e = e.join(other.select("src").distinct(), "src", "left_semi")
                pairs[a, b] = cut(e.select("src", "dst"))
            now = {k: v.count() for k, v in pairs.items()}
            if now == sizes:
                break
            sizes = now
        return joined(pattern, pairs, cand), {"rounds": rounds, "edges": sum(sizes.values())}
    if plans == "first":
        return joined(pattern, pairs, cand, hint="shuffle_hash"), {"plans": 1}
    orders = join_orders(list(pairs), most)
    pairs = {k: cut(v) for k, v in pairs.items()}
    best = None
    for order in orders or [[]]:
        start = time.perf_counter()
        df = joined(pattern, pairs, cand, order, "shuffle_hash")
        df.count()
        took = time.perf_counter() - start
        if best is None or took < best[0]:
            best = took, order, df
    return best[2], {"plans": len(orders), "capped": len(orders) >= most, "best": best[1], "seconds": best[0]}


def local_semijoin(graph: PropertyGraph, pattern: TreePattern, index: Reach | None = None) -> tuple[DataFrame, dict[str, DataFrame]]:
    """Each edge reduces its own two candidate sets once, without looking further; then joins.
    Returns the answers and the candidates that are left.  Of a cluster index each
    ancestor-descendant edge reads the cluster of its ends' kinds alone."""
    pattern = conjunctive(pattern)
    p = Pipeline(graph, pattern, Options(index=index, force_index=index is not None))
    operators = dict(p.operators)
    if isinstance(index, ClusterIndex):
        operators |= {n.name: index.of(pattern.nodes[pattern.parent[n.name]].kind, n.kind) for n in pattern.root.walk() if pattern.parent[n.name] and n.edge == "ad"}
    cand = plain_candidates(graph, pattern)
    kept = dict(cand)
    for n in pattern.root.walk():
        up = pattern.parent[n.name]
        if up:
            kept[up] = kept[up].join(operators[n.name].reaching(cand[up], cand[n.name]), "node_id", "left_semi")
            kept[n.name] = kept[n.name].join(operators[n.name].reachable(cand[up], cand[n.name]), "node_id", "left_semi")
    pairs = {}
    for n in pattern.root.walk():
        up = pattern.parent[n.name]
        if up:
            ends = {"src": kept[up], "dst": kept[n.name]}
            found = operators[n.name].pairs(kept[up], kept[n.name])
            # an index over kinds whose ids differ in type has the widest
            pairs[up, n.name] = found.select(*[F.col(c).try_cast(rows.schema["node_id"].dataType).alias(c) for c, rows in ends.items()])
    return joined(pattern, pairs, kept), kept


def pairwise_filter(sources: DataFrame, targets: DataFrame, closure: DataFrame) -> DataFrame:
    """Set reachability by testing every pair (the ablation that contours avoid; for slices only)."""
    every = sources.select(F.col("node_id").alias("src")).crossJoin(targets.select(F.col("node_id").alias("dst")))
    return every.join(closure, ["src", "dst"], "left_semi").select(F.col("src").alias("node_id")).distinct()


def satisfying(p: Pipeline, cand: dict[str, DataFrame], name: str, formula: Formula | None = None) -> DataFrame:
    """Candidates of a node for which its formula holds, each variable a semi-join with the node's own
    candidates, each negation an anti-join, each alternative a union."""
    rows = cand[name].select("node_id")
    formula = p.pattern.nodes[name].formula if formula is None else formula
    if formula == TRUE:
        return rows
    if formula == FALSE:
        return rows.limit(0)
    if isinstance(formula, Var):
        child = formula.name
        below = satisfying(p, cand, child)
        for c in p.pattern.children(child, True):  # a predicate node has no backbone children; kept for any tree
            below = p.operators[c.name].reaching(below, cand[c.name])
        return p.operators[child].reaching(rows, below)
    if isinstance(formula, Not):
        return rows.join(satisfying(p, cand, name, formula.inner), "node_id", "left_anti")
    parts = [satisfying(p, cand, name, f) for f in formula.parts()]
    if isinstance(formula, And):
        return reduce(lambda a, b: a.join(b, "node_id", "left_semi"), parts)
    return reduce(DataFrame.union, parts).distinct()


def naive_evaluate(graph: PropertyGraph, pattern: TreePattern, index: Reach | None = None) -> DataFrame:
    """One full join of all backbone edges over unpruned candidates, predicates as semi- and anti-joins where
    they stand, then DISTINCT.  No round of the pattern engine is used."""
    p = Pipeline(graph, pattern, Options(index=index))
    cand = plain_candidates(graph, pattern)
    kept = {n: satisfying(p, cand, n) if pattern.nodes[n].formula != TRUE else cand[n] for n in pattern.backbone()}
    pairs = {(pattern.parent[n], n): p.operators[n].pairs(kept[pattern.parent[n]], kept[n]) for n in pattern.backbone() if pattern.parent[n]}
    return joined(pattern, pairs, kept)


def tree_rows(graph: PropertyGraph, piece: TreePattern) -> DataFrame:
    """(grp, path, level, node_id, qnode) of the nodes that match a tree piece: ``grp`` is the node of the
    root's kind above them, ``path`` the ids on the way down from it (a sequence code)."""
    root = piece.root
    kinds: dict[str, list[EdgeSet]] = {root.kind: []}
    for n in piece.root.walk():
        if n.kind not in kinds:
            paths = graph.kind_paths(root.kind, n.kind) or []
            trees = [x for x in paths if all(e.role == "tree" for e in x)]
            if len(trees) != 1:
                raise ValueError(f"{n.kind} is not below {root.kind} by tree edges alone")
            kinds[n.kind] = trees[0]
    parts = []
    for n in piece.root.walk():
        rows = candidates(graph, n).select("node_id", F.array("node_id").alias("path"), F.col("node_id").alias("top"))
        for e in reversed(kinds[n.kind]):
            up = e.df.select(F.col("dst").alias("top"), F.col("src").alias("above"))
            rows = rows.join(up, "top").select("node_id", F.concat(F.array("above"), "path").alias("path"), F.col("above").alias("top"))
        parts.append(rows.select(F.col("top").alias("grp"), F.transform("path", lambda x: x.cast("string")).alias("path"), F.size("path").alias("level"), F.col("node_id").cast("string").alias("node_id"), F.lit(n.name).alias("qnode")))
    return reduce(DataFrame.union, parts)


def twig_engine(method: str = "paths") -> Engine:
    """Evaluates a tree piece by the holistic twig joins: stack-encoded paths, or nested results."""
    def run(graph: PropertyGraph, piece: TreePattern) -> DataFrame:
        from treelogic.baselines import twigs
        from treelogic.evaluate.engine import id_type

        if piece.size() == 1:
            return candidates(graph, piece.root).select(F.col("node_id").alias(piece.root.name))
        rows = tree_rows(graph, piece)
        found = (twigs.paths_of if method == "paths" else twigs.nested_of)(rows, piece)
        return found.select(*[F.col(n).cast(id_type(graph, piece.nodes[n].kind)).alias(n) for n in piece.outputs()])

    return run


def decompose(graph: PropertyGraph, pattern: TreePattern) -> tuple[list[TreePattern], list[tuple[str, str]]]:
    """Cuts a conjunctive pattern where an edge must use a reference edge set: (tree pieces, cut edges)."""
    pattern = conjunctive(pattern)
    cuts = []
    for n in pattern.root.walk():
        up = pattern.parent[n.name]
        if up:
            paths = graph.kind_paths(pattern.nodes[up].kind, n.kind) or []
            if not paths or any(e.role == "ref" for path in paths for e in path):
                cuts.append((up, n.name))
    tops = [pattern.root.name, *[b for _, b in cuts]]
    below = {b for _, b in cuts}

    def piece(n: PatternNode) -> PatternNode:
        return replace(n, output=True, children=tuple(piece(c) for c in n.children if c.name not in below))

    return [TreePattern(piece(replace(pattern.nodes[t], edge="ad"))) for t in tops], cuts


def decompose_evaluate(graph: PropertyGraph, pattern: TreePattern, engine: Engine | None = None) -> tuple[DataFrame, dict]:
    """Evaluates the tree pieces one by one, by the stack-encoded twig join unless another engine is given,
    and joins them on the reference edges that were cut."""
    pieces, cuts = decompose(graph, pattern)
    whole = conjunctive(pattern)
    p = Pipeline(graph, whole, Options())
    cand = plain_candidates(graph, whole)
    tables = {piece.root.name: (engine or twig_engine())(graph, piece) for piece in pieces}
    rows = tables[whole.root.name]
    todo = list(cuts)
    while todo:
        a, b = next(c for c in todo if c[0] in rows.columns)
        todo.remove((a, b))
        pairs = p.operators[b].pairs(cand[a], cand[b]).select(F.col("src").alias(a), F.col("dst").alias(b))
        rows = rows.join(pairs, a).join(tables[b], b)
    return rows.select(*pattern.outputs()).distinct(), {"subqueries": len(pieces), "merges": 2 * len(cuts)}


