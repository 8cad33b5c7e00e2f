"""Reach operators: the three set-level questions that every pattern edge asks.

``reaching(A, B)``: rows of A whose node has a nonempty path to a node of B;
``reachable(A, B)``: rows of B whose node has a nonempty path from a node of A;
``pairs(A, B)``: all such (src, dst), each once.  A and B are tables with
``node_id``.  ``Children`` answers the same for single edges.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.graph.model import EdgeSet, PropertyGraph, through
from treelogic.plans import cut, small


class Reach:
    """One way to answer; all ways agree (the tests compare them)."""

    reflexive = False

    def reaching(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        raise NotImplementedError

    def reachable(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        raise NotImplementedError

    def pairs(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        raise NotImplementedError

    def columns(self, end: str) -> set[str]:
        """Columns, besides ``node_id``, that rows at one end (source or target) should carry where they have them."""
        return set()

    def walked(self, rows: DataFrame, at: str, name: str, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """The rows, whose column ``at`` holds sources, once for each target that it reaches, the target as ``name``."""
        return rows.join(small(cut(self.pairs(sources, targets).distinct().toDF(at, name))), at)

    def weighed(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """(node_id, m): for each source the sum of ``n`` over the targets that it reaches; sources that reach none are left out."""
        return self.pairs(sources, targets).distinct().join(targets.select(F.col("node_id").alias("dst"), "n"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.sum("n").alias("m"))


def _ids(df: DataFrame, name: str) -> DataFrame:
    return df.select(F.col("node_id").alias(name))


def _among(rows: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows whose ``node_id`` is among the ids, with all their columns."""
    return rows.join(ids.select("node_id"), "node_id", "left_semi").select(*rows.columns)


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.union, parts)


def _none(df: DataFrame, *names: str) -> DataFrame:
    return df.sparkSession.createDataFrame([], ", ".join(f"{n} long" for n in names))


class KindPaths(Reach):
    """Paths over the graph of kinds: each is a chain of equi-joins along edge sets.

    Where the rows at hand carry the other end's id, a step needs no edge table.
    Results keep the columns of their rows.
    """

    def __init__(self, paths: list[list[EdgeSet]]):
        self.paths = [through(p) for p in paths]

    def link(self) -> EdgeSet | None:
        """The edge set, if that is all there is and one end holds the other's id."""
        if len(self.paths) == 1 and len(self.paths[0]) == 1 and self.paths[0][0].holder:
            return self.paths[0][0]
        return None

    def columns(self, end: str) -> set[str]:
        """Columns of ids that rows at one end of the paths should carry."""
        at = 0 if end == "source" else -1
        return {p[at].column for p in self.paths if p[at].holder == end}

    def reaching(self, sources, targets):
        if not self.paths:
            return sources.limit(0)
        # paths that end alike share their last steps
        memo: dict[tuple, DataFrame] = {(): targets}

        def back(path: tuple[EdgeSet, ...]) -> DataFrame:
            names = tuple(e.name for e in path)
            if names not in memo:
                memo[names] = path[0].back(back(path[1:]))
            return memo[names]

        if len(self.paths) == 1:
            return self.paths[0][0].sources_to(sources, back(tuple(self.paths[0][1:])))
        found = _union([back(tuple(p)).select("node_id") for p in self.paths])
        return sources.join(found, "node_id", "left_semi").select(*sources.columns)

    def reachable(self, sources, targets):
        if not self.paths:
            return targets.limit(0)
        memo: dict[tuple, DataFrame] = {(): sources}

        def ahead(path: tuple[EdgeSet, ...]) -> DataFrame:
            names = tuple(e.name for e in path)
            if names not in memo:
                memo[names] = path[-1].ahead(ahead(path[:-1]))
            return memo[names]

        if len(self.paths) == 1:
            return self.paths[0][-1].targets_from(ahead(tuple(self.paths[0][:-1])), targets)
        found = _union([ahead(tuple(p)).select("node_id") for p in self.paths])
        return targets.join(found, "node_id", "left_semi").select(*targets.columns)

    def pairs(self, sources, targets):
        if not self.paths:
            return _none(sources, "src", "dst")
        out = []
        for path in self.paths:
            if len(path) == 1:
                out.append(path[0].between(sources, targets))
                continue
            first, last = path[0], path[-1]
            if first.held_by("source", sources):
                rows = sources.select(F.col("node_id").alias("src"), F.col(first.column).alias("dst"))
            else:
                rows = first.df.join(_ids(sources, "src"), "src", "left_semi").select("src", "dst")
            for e in path[1:-1]:
                rows = rows.withColumnRenamed("dst", "via").join(e.df.select(F.col("src").alias("via"), "dst"), "via").select("src", "dst")
            if last.held_by("target", targets):
                end = targets.select(F.col(last.column).alias("via"), F.col("node_id").alias("dst"))
            else:
                end = last.df.join(_ids(targets, "dst"), "dst", "left_semi").select(F.col("src").alias("via"), "dst")
            out.append(rows.withColumnRenamed("dst", "via").join(end, "via").select("src", "dst"))
        found = _union(out)
        return found if self.link() else found.distinct()


class Children(Reach):
    """Single edges."""

    def __init__(self, edges: DataFrame, sets: list[EdgeSet] | None = None):
        self.edges, self.sets = edges, sets

    def reaching(self, sources, targets):
        parents = self.edges.join(_ids(targets, "dst"), "dst", "left_semi").select(F.col("src").alias("node_id"))
        return _among(sources, parents)

    def reachable(self, sources, targets):
        children = self.edges.join(_ids(sources, "src"), "src", "left_semi").select(F.col("dst").alias("node_id"))
        return _among(targets, children)

    def pairs(self, sources, targets):
        return self.edges.join(_ids(sources, "src"), "src", "left_semi").join(_ids(targets, "dst"), "dst", "left_semi").select("src", "dst").distinct()


class Frontier(Reach):
    """Semi-naive expansion without an index: each round goes one edge on from the nodes found last.

    The other set is treated as one node, so a node is expanded once whatever
    the number of targets; ``pairs`` expands from the sources only.
    """

    def __init__(self, edges: DataFrame, most_rounds: int = 10_000):
        self.edges, self.most_rounds = edges.select("src", "dst"), most_rounds

    def _closure(self, start: DataFrame, frm: str, to: str) -> DataFrame:
        found = front = cut(self.edges.join(start.select(F.col("node_id").alias(frm)), frm, "left_semi").select(F.col(to).alias("node_id")).distinct())
        for _ in range(self.most_rounds):
            step = self.edges.join(front.select(F.col("node_id").alias(frm)), frm, "left_semi").select(F.col(to).alias("node_id")).distinct()
            front = cut(step.join(found, "node_id", "left_anti"))
            if front.isEmpty():
                return found
            found = cut(found.union(front))
        raise RuntimeError("the expansion did not end")

    def reaching(self, sources, targets):
        return _among(sources, self._closure(targets, "dst", "src"))

    def reachable(self, sources, targets):
        return _among(targets, self._closure(sources, "src", "dst"))

    def pairs(self, sources, targets):
        found = front = cut(self.edges.join(_ids(sources, "src"), "src", "left_semi").distinct())
        for _ in range(self.most_rounds):
            step = front.select("src", F.col("dst").alias("via")).join(self.edges.select(F.col("src").alias("via"), "dst"), "via").select("src", "dst").distinct()
            front = cut(step.join(found, ["src", "dst"], "left_anti"))
            if front.isEmpty():
                return found.join(_ids(targets, "dst"), "dst", "left_semi").select("src", "dst")
            found = cut(found.union(front))
        raise RuntimeError("the expansion did not end")


def closure(edges: DataFrame, most_rounds: int = 64) -> DataFrame:
    """Strict transitive closure (src, dst) by doubling: rounds grow with the logarithm of the longest path."""
    found = cut(edges.select("src", "dst").distinct())
    n = found.count()
    for _ in range(most_rounds):
        step = found.select("src", F.col("dst").alias("via")).join(found.select(F.col("src").alias("via"), "dst"), "via").select("src", "dst")
        found = cut(found.union(step).distinct())
        if (m := found.count()) == n:
            return found
        n = m
    raise RuntimeError("the closure did not settle")


class Closure(Reach):
    """The whole closure as a table; for slices and tests."""

    def __init__(self, edges: DataFrame | None = None, pairs: DataFrame | None = None):
        self.table = closure(edges) if pairs is None else pairs

    def reaching(self, sources, targets):
        return Children(self.table).reaching(sources, targets)

    def reachable(self, sources, targets):
        return Children(self.table).reachable(sources, targets)

    def pairs(self, sources, targets):
        return Children(self.table).pairs(sources, targets)


class Interval(Reach):
    """Containment of [pre, post] intervals inside a group (a document's tree)."""

    def __init__(self, nodes: DataFrame, group: str = "page_id"):
        self.nodes = nodes.select("node_id", F.col(group).alias("grp"), "pre", "post")

    def _both(self, sources, targets) -> DataFrame:
        a = self.nodes.join(sources.select("node_id"), "node_id", "left_semi").select(F.col("node_id").alias("src"), "grp", F.col("pre").alias("a"), F.col("post").alias("b"))
        c = self.nodes.join(targets.select("node_id"), "node_id", "left_semi").select(F.col("node_id").alias("dst"), "grp", F.col("pre").alias("c"))
        return a.join(c, (a["grp"] == c["grp"]) & (c["c"] > a["a"]) & (c["c"] < a["b"])).select("src", "dst")

    def reaching(self, sources, targets):
        return _among(sources, self._both(sources, targets).select(F.col("src").alias("node_id")))

    def reachable(self, sources, targets):
        return _among(targets, self._both(sources, targets).select(F.col("dst").alias("node_id")))

    def pairs(self, sources, targets):
        return self._both(sources, targets).distinct()


class Reflexive(Reach):
    """Another operator's answers and every node's own: the index's literal test, for comparison."""

    reflexive = True

    def __init__(self, inner: Reach):
        self.inner = inner

    def reaching(self, sources, targets):
        return _among(sources, self.inner.reaching(sources, targets).select("node_id").union(targets.select("node_id")))

    def reachable(self, sources, targets):
        return _among(targets, self.inner.reachable(sources, targets).select("node_id").union(sources.select("node_id")))

    def pairs(self, sources, targets):
        own = sources.select("node_id").join(targets.select("node_id"), "node_id", "left_semi").select(F.col("node_id").alias("src"), F.col("node_id").alias("dst"))
        return self.inner.pairs(sources, targets).union(own).distinct()

    def weighed(self, sources, targets):
        if (sums := getattr(self.inner, "summed", None)) is not None:
            return sums(sources, targets, True)
        return super().weighed(sources, targets)


def children_of(graph: PropertyGraph, source: str | None, target: str | None) -> Reach:
    """The operator for a parent-child edge."""
    sets = graph.between(source, target)
    if source and target and sets and all(e.holder for e in sets):
        return KindPaths([[e] for e in sets])
    if not sets:
        return Children(_none(next(iter(graph.nodes.values())), "src", "dst"))
    return Children(_union([e.df.select("src", "dst") for e in sets]), sets)


def choose(graph: PropertyGraph, source: str | None, target: str | None, index: Reach | None = None, force: bool = False) -> Reach:
    """The operator for an ancestor-descendant edge: paths of kinds where no cycle of kinds lies
    between (unless ``force`` asks for the index), else the index, else expansion restricted to the kinds that
    can lie on a path."""
    if source and target and not (force and index is not None):
        paths = graph.kind_paths(source, target)
        if paths is not None:
            return KindPaths(paths)
    if index is not None:
        return index.between(source, target) if source and target and hasattr(index, "between") else index
    sets = graph.edges
    if target:
        leads = {target}
        while more := {e.source for e in sets if e.target in leads} - leads:
            leads |= more
        sets = [e for e in sets if e.target in leads]
    return Frontier(_union([e.df.select("src", "dst") for e in sets]).distinct())
