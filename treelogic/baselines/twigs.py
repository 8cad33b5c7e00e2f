"""Holistic twig joins on trees, and the pool-based join on acyclic graphs.

The tree algorithms run inside one tree at a time (a document, a conversation):
rows carry ``grp``, ``pre``, ``post`` and the pattern nodes they match.
"""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.baselines.joins import conjunctive
from treelogic.evaluate.engine import Options, Pipeline, atom_column
from treelogic.graph.model import PropertyGraph
from treelogic.plans import cut
from treelogic.query.pattern import TreePattern


def streams(nodes: DataFrame, pattern: TreePattern, group: str = "page_id") -> DataFrame:
    """(grp, pre, post, level, node_id, qnode): one row for each pattern node that a tree node matches."""
    tests = F.array_compact(F.array(*[F.when(atom_column(nodes, u), F.lit(u.name)) for u in pattern.root.walk()]))
    return nodes.select(F.col(group).alias("grp"), "pre", "post", "level", "node_id", F.explode(tests).alias("qnode"))


def _path_solver(path: list[str], edges: list[str], kind: str = "int64"):
    """Solutions of one root-to-leaf path in one tree, with a stack for each pattern node."""
    def solve(tree: pd.DataFrame) -> pd.DataFrame:
        stacks: list[list[tuple]] = [[] for _ in path]
        place = {n: i for i, n in enumerate(path)}
        out: list[tuple] = []
        # deeper pattern nodes first at one tree node, so that a node is not its own ancestor
        tree = tree.assign(__i=tree["qnode"].map(place)).sort_values(["pre", "__i"], ascending=[True, False])
        for pre, post, level, node, i in zip(tree["pre"], tree["post"], tree["level"], tree["node_id"], tree["__i"]):
            for s in stacks:
                while s and s[-1][1] < pre:
                    s.pop()
            if i and not stacks[i - 1]:
                continue
            entry = (pre, post, level, node, len(stacks[i - 1]) if i else 0)
            if i < len(path) - 1:
                stacks[i].append(entry)
                continue

            def back(k: int, e: tuple, tail: tuple) -> None:
                if k == 0:
                    out.append((e[3], *tail))
                    return
                for up in stacks[k - 1][:e[4]]:
                    if up[0] < e[0] and (edges[k] == "ad" or up[2] == e[2] - 1):
                        back(k - 1, up, (e[3], *tail))

            back(i, entry, ())
        return pd.DataFrame(out, columns=path, dtype=kind)

    return solve


def _numbered(tree: pd.DataFrame) -> pd.DataFrame:
    """A tree whose nodes carry sequence codes (``path``) with the numbers of entering and leaving."""
    tree = tree.assign(path=[tuple(p) for p in tree["path"]]).sort_values("path", kind="stable")
    clock, pre, post = 0, {}, {}
    stack: list[tuple] = []
    for path in tree["path"]:
        if path in pre:
            continue
        while stack and path[:len(stack[-1])] != stack[-1]:
            clock += 1
            post[stack.pop()] = clock
        clock += 1
        pre[path] = clock
        stack.append(path)
    while stack:
        clock += 1
        post[stack.pop()] = clock
    return tree.assign(pre=[pre[p] for p in tree["path"]], post=[post[p] for p in tree["path"]])


def _on_codes(solve):
    def run(tree: pd.DataFrame) -> pd.DataFrame:
        return solve(_numbered(tree))

    return run


def paths_of(rows: DataFrame, pattern: TreePattern) -> DataFrame:
    """Stack-encoded path solutions over nodes with sequence codes (grp, path, level, node_id, qnode); all ids as text."""
    leaves = [n.name for n in pattern.root.walk() if not n.children]
    tables = []
    for leaf in leaves:
        path = pattern.path(leaf)
        solve = _on_codes(_path_solver(path, [pattern.nodes[n].edge for n in path], "str"))
        tables.append(rows.filter(F.col("qnode").isin(path)).groupBy("grp").applyInPandas(solve, ", ".join(f"`{n}` string" for n in path)))
    return reduce(lambda a, b: a.join(b, [c for c in a.columns if c in b.columns]), tables).select(*pattern.outputs()).distinct()


def nested_of(rows: DataFrame, pattern: TreePattern) -> DataFrame:
    """Nested results over nodes with sequence codes; all ids as text."""
    outputs = pattern.outputs()
    table = rows.groupBy("grp").applyInPandas(_on_codes(_nested_solver(pattern, "str")), ", ".join([*[f"`{n}` string" for n in outputs], "cells long"]))
    return table.select(*outputs).distinct()


def twig_paths(nodes: DataFrame, pattern: TreePattern, group: str = "page_id") -> tuple[DataFrame, dict[str, int]]:
    """Stack-encoded path solutions for every root-to-leaf path of the pattern, joined on shared prefixes."""
    pattern = conjunctive(pattern)
    rows = streams(nodes, pattern, group)
    leaves = [n.name for n in pattern.root.walk() if not n.children]
    tables, sizes = [], {}
    for leaf in leaves:
        path = pattern.path(leaf)
        edges = [pattern.nodes[n].edge for n in path]

        mine = rows.filter(F.col("qnode").isin(path))
        tables.append(cut(mine.groupBy("grp").applyInPandas(_path_solver(path, edges), ", ".join(f"`{n}` long" for n in path))))
        sizes[leaf] = tables[-1].count()
    answer = reduce(lambda a, b: a.join(b, [c for c in a.columns if c in b.columns]), tables)
    return answer.select(*pattern.outputs()).distinct(), {"path_rows": sum(sizes.values()), "merges": len(tables) - 1}


def _nested_solver(pattern: TreePattern, kind: str = "int64"):
    """In post order every tree node keeps, for each pattern node it satisfies, the matches of its children inside it."""
    outputs = pattern.outputs()
    order = [n.name for n in pattern.postorder()]

    def solve(tree: pd.DataFrame) -> pd.DataFrame:
        place = {n: i for i, n in enumerate(order)}
        tree = tree.assign(__i=tree["qnode"].map(place)).sort_values(["post", "__i"], ascending=[True, True])
        held: dict[str, list[tuple]] = {n: [] for n in order}
        cells = 0
        for pre, post, level, node, q in zip(tree["pre"], tree["post"], tree["level"], tree["node_id"], tree["qnode"]):
            inside = []
            for c in pattern.nodes[q].children:
                found = []
                for m in reversed(held[c.name]):
                    if m[1] < pre:
                        break
                    if m[0] > pre and (c.edge == "ad" or m[2] == level + 1):
                        found.append(m)
                if not found:
                    break
                inside.append((c.name, found))
            else:
                held[q].append((pre, post, level, node, inside))
                cells += 1 + sum(len(f) for _, f in inside)

        def rows(q: str, m: tuple) -> list[dict]:
            out = [{q: m[3]}]
            for name, found in m[4]:
                out = [a | b for a in out for f in found for b in rows(name, f)]
            return out

        found = [tuple(r[o] for o in outputs) + (cells,) for m in held[pattern.root.name] for r in rows(pattern.root.name, m)]
        return pd.DataFrame(found, columns=[*outputs, "cells"]).astype({n: kind for n in outputs} | {"cells": "int64"})

    return solve


def twig_nested(nodes: DataFrame, pattern: TreePattern, group: str = "page_id") -> tuple[DataFrame, dict[str, int]]:
    """Nested results: tuples are made at the root only."""
    pattern = conjunctive(pattern)
    outputs = pattern.outputs()
    table = cut(streams(nodes, pattern, group).groupBy("grp").applyInPandas(_nested_solver(pattern), ", ".join(f"`{n}` long" for n in [*outputs, "cells"])))
    return table.select(*outputs).distinct(), {"rows": table.count()}


def kind_order(graph: PropertyGraph) -> list[str] | None:
    """The kinds, sources first; None if kinds lie on a cycle."""
    left, out = list(graph.nodes), []
    while left:
        free = [k for k in left if not any(e.target == k and e.source in left for e in graph.edges)]
        if not free:
            return None
        out += free
        left = [k for k in left if k not in free]
    return out


def _tests(graph: PropertyGraph, pattern: TreePattern, kind: str, bit: dict[str, int]) -> DataFrame:
    """(node_id, tests) of all nodes of a kind: bits of the pattern nodes whose tests they pass."""
    rows = graph.nodes[kind]
    tests = [F.when(atom_column(rows, u), F.lit(bit[u.name])).otherwise(F.lit(0)) for u in pattern.root.walk() if u.kind in (None, kind)]
    return rows.select("node_id", reduce(lambda a, b: a.bitwiseOR(b), tests, F.lit(0)).cast("long").alias("tests"))


def prefilter(graph: PropertyGraph, pattern: TreePattern) -> dict[str, DataFrame]:
    """Two passes over the whole graph with a set of pattern nodes at every data node: which sub-patterns
    it satisfies or has below it, then which of them have the needed ancestors.

    Where no kinds lie on a cycle every edge is visited once in each pass, kind by
    kind; otherwise the sets grow to a fixpoint.
    """
    pattern = conjunctive(pattern)
    names = [n.name for n in pattern.root.walk()]
    bit = {n: 1 << i for i, n in enumerate(names)}
    down_needs = {n: (sum(bit[c.name] for c in pattern.nodes[n].children if c.edge == "pc"), sum(bit[c.name] for c in pattern.nodes[n].children if c.edge == "ad")) for n in names}
    up_needs = {n: ((0, 0) if pattern.parent[n] is None else (bit[pattern.parent[n]], 0) if pattern.nodes[n].edge == "pc" else (0, bit[pattern.parent[n]])) for n in names}

    def met(needs: dict[str, tuple[int, int]], allowed: str):
        """Bits that may hold and whose needs are met by what is near and by what is anywhere along the edges."""
        has = F.lit(0).cast("long")
        for n in names:
            pc, ad = needs[n]
            good = (F.col(allowed).bitwiseAND(F.lit(bit[n])) != 0) & (F.col("near").bitwiseAND(F.lit(pc)) == pc) & (F.col("every").bitwiseAND(F.lit(ad)) == ad)
            has = has.bitwiseOR(F.when(good, F.lit(bit[n])).otherwise(0).cast("long"))
        return has

    order = kind_order(graph)
    if order is not None:
        def one_pass(tests: dict[str, DataFrame], kinds: list[str], needs, frm: str, to: str) -> dict[str, DataFrame]:
            """(node_id, has, far) of each kind; the kinds that it looks at come before it."""
            state: dict[str, DataFrame] = {}
            for kind in kinds:
                seen = []
                for e in graph.edges:
                    here, there = (e.source, e.target) if frm == "src" else (e.target, e.source)
                    if here == kind:
                        far = state[there].filter("has <> 0 or far <> 0").select(F.col("node_id").alias(to), "has", F.col("has").bitwiseOR(F.col("far")).alias("all"))
                        seen.append(e.df.join(far, to).select(F.col(frm).alias("node_id"), "has", "all"))
                rows = tests[kind]
                if seen:
                    sums = reduce(DataFrame.union, seen).groupBy("node_id").agg(F.bit_or("has").alias("near"), F.bit_or("all").alias("every"))
                    rows = rows.join(sums, "node_id", "left").fillna(0, ["near", "every"])
                else:
                    rows = rows.withColumn("near", F.lit(0).cast("long")).withColumn("every", F.lit(0).cast("long"))
                state[kind] = cut(rows.select("node_id", met(needs, "tests").alias("has"), F.col("every").alias("far")))
            return state

        down = one_pass({k: _tests(graph, pattern, k, bit) for k in order}, order[::-1], down_needs, "src", "dst")
        up = one_pass({k: df.select("node_id", F.col("has").alias("tests")) for k, df in down.items()}, order, up_needs, "dst", "src")
        kinds = {n: [pattern.nodes[n].kind] if pattern.nodes[n].kind else order for n in names}
        return {n: reduce(DataFrame.union, [up[k].filter(F.col("has").bitwiseAND(F.lit(bit[n])) != 0).select("node_id") for k in kinds[n]]) for n in names}

    edges = cut(graph.all_edges())
    nodes = reduce(DataFrame.union, [_tests(graph, pattern, k, bit) for k in graph.nodes])

    def sweep(state: DataFrame, frm: str, to: str, needs: dict[str, tuple[int, int]]) -> DataFrame:
        """Least fixpoint of: a bit holds at a node if it may and its needs are met along the edges."""
        state = cut(state.withColumn("has", F.lit(0).cast("long")).withColumn("far", F.lit(0).cast("long")))
        while True:
            told = state.filter("has <> 0 or far <> 0").select(F.col("node_id").alias(to), "has", F.col("has").bitwiseOR(F.col("far")).alias("all"))
            seen = edges.join(told, to).groupBy(F.col(frm).alias("node_id")).agg(F.bit_or("has").alias("near"), F.bit_or("all").alias("every"))
            joined = state.withColumnRenamed("has", "had").withColumnRenamed("far", "was").join(seen, "node_id", "left").fillna(0, ["near", "every"])
            after = cut(joined.select("node_id", "tests", met(needs, "tests").alias("has"), F.col("every").alias("far"), "had", "was"))
            changed = after.filter("has <> had or far <> was").isEmpty()
            state = after.drop("had", "was")
            if changed:
                return state

    down = sweep(nodes, "src", "dst", down_needs)
    up = sweep(down.select("node_id", F.col("has").alias("tests")), "dst", "src", up_needs)
    return {n: up.filter(F.col("has").bitwiseAND(F.lit(bit[n])) != 0).select("node_id") for n in names}


def pool_twig(graph: PropertyGraph, pattern: TreePattern, filtered: bool = True) -> tuple[DataFrame, dict[str, int]]:
    """Pool join on an acyclic graph: a pattern node's pool holds the nodes that pass the two-pass filter
    (without it, every candidate), and pools are joined edge by edge.  The original's stacks and its
    tree-like index have no counterpart here: edges are found by joins of edge tables."""
    from treelogic.baselines.joins import joined, plain_candidates

    pattern = conjunctive(pattern)
    p = Pipeline(graph, pattern, Options())
    pools = prefilter(graph, pattern) if filtered else plain_candidates(graph, pattern)
    pools = {n: cut(df) for n, df in pools.items()}
    pairs = {(pattern.parent[n.name], n.name): p.operators[n.name].pairs(pools[pattern.parent[n.name]], pools[n.name]) for n in pattern.root.walk() if pattern.parent[n.name]}
    return joined(pattern, pairs, pools), {"pool_nodes": sum(df.count() for df in pools.values())}
