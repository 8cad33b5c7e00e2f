"""Further reach operators: tree codes, a tree cover with surplus lists, a table of pairs by label.

A tree code is the list of a node's ancestors from the root, itself last: a Dewey
code whose steps are ids, so that no parent's children need numbering in one
task.  Ancestor tests join the elements of a code by equality, where intervals
would need a range join.  Codes take nodes times depth of space.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.graph.model import EdgeSet, PropertyGraph
from treelogic.index.reach import Children, KindPaths, Reach, _among, closure
from treelogic.index.scc import condense
from treelogic.plans import cut


def tree_codes(nodes: DataFrame, edges: DataFrame, most_rounds: int = 40) -> DataFrame:
    """(node_id, code) of a forest whose edges (src, dst) lead from parents to children.

    Each round puts the code of the topmost known ancestor in front, so rounds
    grow with the logarithm of the depth.  A node with two parents is an error,
    as are rounds that run out (a cycle).
    """
    parents = edges.groupBy("dst").agg(F.count_distinct("src").alias("n"), F.min("src").alias("top"))
    one = F.when(F.col("n") > 1, F.raise_error(F.lit("a node of a tree has two parents")).cast(parents.schema["top"].dataType)).otherwise(F.col("top"))
    codes = nodes.select("node_id").distinct().join(parents.select(F.col("dst").alias("node_id"), one.alias("top")), "node_id", "left").withColumn("code", F.array("node_id"))
    for _ in range(most_rounds):
        codes = cut(codes)
        if codes.filter("top is not null").isEmpty():
            return codes.select("node_id", "code")
        above = codes.select(F.col("node_id").alias("top"), F.col("top").alias("next"), F.col("code").alias("before"))
        longer = F.concat(F.coalesce("before", F.array().cast(codes.schema["code"].dataType)), "code")
        codes = codes.join(above, "top", "left").select("node_id", F.col("next").alias("top"), longer.alias("code"))
    raise RuntimeError("the edges are no forest")


def _above(codes: DataFrame, strict: bool) -> DataFrame:
    """(src, dst): the ancestors of the coded nodes, the nodes themselves included unless ``strict``."""
    code = F.slice("code", 1, F.size("code") - 1) if strict else F.col("code")
    return codes.select(F.explode(code).alias("src"), F.col("node_id").alias("dst"))


class TreeCode(Reach):
    """Ancestors and descendants in a forest by the codes of the lower nodes."""

    def __init__(self, nodes: DataFrame, edges: DataFrame):
        self.codes = tree_codes(nodes, edges)

    def _links(self, targets: DataFrame) -> DataFrame:
        return _above(self.codes.join(targets.select("node_id"), "node_id", "left_semi"), strict=True)

    def reaching(self, sources, targets):
        return _among(sources, self._links(targets).select(F.col("src").alias("node_id")))

    def reachable(self, sources, targets):
        return Children(self._links(targets)).reachable(sources, targets)

    def pairs(self, sources, targets):
        return self._links(targets).join(sources.select(F.col("node_id").alias("src")), "src", "left_semi").select("src", "dst").distinct()


class TreeCover(Reach):
    """A spanning forest's codes and, for what the forest misses, surplus lists; on any digraph.

    A node's surplus list holds the tops of the subtrees that it reaches other
    than down the forest; a top below another of the same list, or below the node
    itself, is left out.  Lists come from the edges outside the forest by
    expansion against the edges, a job for each step of depth; they can grow to
    nodes times such edges, which is why it serves graphs that are nearly trees.
    """

    def __init__(self, scc: DataFrame, codes: DataFrame, surplus: DataFrame):
        self.scc, self.codes, self.surplus = scc, codes, surplus

    @classmethod
    def build(cls, nodes: DataFrame, edges: DataFrame, acyclic: bool = False, most_rounds: int = 10_000) -> TreeCover:
        if acyclic:
            scc = cut(nodes.select("node_id", F.col("node_id").alias("comp"), F.lit(False).alias("cyclic")))
            dag = cut(edges.select("src", "dst").distinct())
        else:
            scc, dag = condense(nodes, edges)
        tree = cut(dag.groupBy("dst").agg(F.min("src").alias("src")).select("src", "dst"))
        codes = cut(tree_codes(scc.select(F.col("comp").alias("node_id")).distinct(), tree))
        of_top = codes.withColumnRenamed("node_id", "top")

        def outside(rows: DataFrame) -> DataFrame:
            """The rows (node, top) whose top is not below the node in the forest."""
            return rows.join(of_top, "top").filter(~F.array_contains("code", F.col("node"))).select("node", "top")

        cross = dag.join(tree, ["src", "dst"], "left_anti").select(F.col("src").alias("node"), F.col("dst").alias("top"))
        found = front = cut(outside(cross))
        for _ in range(most_rounds):
            if front.isEmpty():
                break
            step = dag.join(front.withColumnRenamed("node", "dst"), "dst").select(F.col("src").alias("node"), "top").distinct()
            front = cut(outside(step.join(found, ["node", "top"], "left_anti")))
            found = cut(found.union(front))
        else:
            raise RuntimeError("the surplus lists did not settle")
        below = found.join(of_top, "top").select("node", "top", F.explode(F.slice("code", 1, F.size("code") - 1)).alias("over"))
        covered = below.join(found.withColumnRenamed("top", "over"), ["node", "over"], "left_semi").select("node", "top").distinct()
        return cls(scc, codes, cut(found.join(covered, ["node", "top"], "left_anti")))

    def _links(self, targets: DataFrame) -> DataFrame:
        """(src, dst) components that reach a target's component, and cyclic ones themselves."""
        aimed = self.scc.join(targets.select("node_id"), "node_id", "left_semi").select(F.col("comp").alias("node_id"), "cyclic").distinct()
        codes = self.codes.join(aimed, "node_id", "left_semi")
        beside = self.surplus.join(_above(codes, strict=False).withColumnRenamed("src", "top"), "top").select(F.col("node").alias("src"), "dst")
        own = aimed.filter("cyclic").select(F.col("node_id").alias("src"), F.col("node_id").alias("dst"))
        return _above(codes, strict=True).union(beside).union(own)

    def _placed(self, rows: DataFrame, comp: str, name: str) -> DataFrame:
        return self.scc.join(rows.select("node_id"), "node_id", "left_semi").select(F.col("comp").alias(comp), F.col("node_id").alias(name))

    def reaching(self, sources, targets):
        comps = self._links(targets).select(F.col("src").alias("comp"))
        return _among(sources, self.scc.join(comps, "comp", "left_semi").select("node_id"))

    def reachable(self, sources, targets):
        hit = self._links(targets).join(self._placed(sources, "src", "a"), "src", "left_semi").select(F.col("dst").alias("comp"))
        return _among(targets, self.scc.join(hit, "comp", "left_semi").select("node_id"))

    def pairs(self, sources, targets):
        a, b = self._placed(sources, "src", "a"), self._placed(targets, "dst", "b")
        return self._links(targets).distinct().join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct()

    def stats(self) -> dict[str, int]:
        """Nodes, elements of codes and of surplus lists."""
        return {"nodes": self.scc.count(), "codes": int(self.codes.agg(F.sum(F.size("code"))).first()[0] or 0), "surplus": self.surplus.count()}


class KindCover(Reach):
    """The tree cover of a graph whose kinds lie on no cycle, with nothing written.

    The forest is chosen by kinds: of the edge sets into a kind the first whose
    rows hold their parent is the tree's.  A row then holds the last step of its
    code, and the longer slices of codes are made from the kinds above when they
    are read.  What the forest misses are the other edge sets; a surplus list of a
    node is found at the nodes below it, by their codes, so that no list is
    stored for the nodes above.
    """

    def __init__(self, graph: PropertyGraph):
        self.graph = graph
        #: kind -> the edge set of the forest that leads to it
        self.tree: dict[str, EdgeSet] = {}
        for e in graph.edges:
            if e.role == "tree" and e.holder == "target" and e.rows is not None:
                self.tree.setdefault(e.target, e)

    def codes(self, kind: str, top: str | None = None) -> DataFrame:
        """(node_id, code): the ids from the ancestor of kind ``top`` (None: the root) down to each node of a kind.
        Nodes without such an ancestor have no code from it, and the code from their topmost ancestor without ``top``."""
        rows = self.graph.nodes[kind]
        if kind == top or kind not in self.tree:
            return rows.select("node_id", F.array("node_id").alias("code")).distinct()
        e = self.tree[kind]
        above = self.codes(e.source, top).withColumnRenamed("node_id", "up")
        own = rows.select("node_id", F.col(e.column).alias("up")).distinct()
        if e.source == top:
            return own.filter("up is not null").join(above.select("up"), "up", "left_semi").select("node_id", F.array("up", "node_id").alias("code"))
        wide = f"array<{rows.schema['node_id'].dataType.simpleString()}>"
        before = F.coalesce(F.col("code").cast(wide), F.array().cast(wide))
        return own.join(above, "up", "left" if top is None else "inner").select("node_id", F.concat(before, F.array("node_id")).alias("code"))

    def _slice(self, run: list[EdgeSet]) -> EdgeSet:
        """Steps of the forest, one below the other, as one: the two ends of the codes between their kinds."""
        if len(run) == 1:
            return run[0]
        top, kind = run[0].source, run[-1].target
        id_ = self.graph.nodes[top].schema["node_id"].dataType
        ends = self.codes(kind, top).select(F.col("code")[0].cast(id_).alias("src"), F.col("node_id").alias("dst"))
        return EdgeSet(">".join(e.name for e in run), top, kind, "tree", ends)

    def between(self, source: str, target: str) -> KindPaths:
        """The tests between two kinds: slices of codes, and the entries of surplus lists between them."""
        paths = self.graph.kind_paths(source, target)
        if paths is None:
            raise ValueError("kinds on a cycle")
        found = []
        for path in paths:
            steps, run = [], []
            for e in path:
                if self.tree.get(e.target) is e:
                    run.append(e)
                    continue
                steps += ([self._slice(run)] if run else []) + [e]
                run = []
            found.append(steps + ([self._slice(run)] if run else []))
        return KindPaths(found)

    def _each(self) -> list[KindPaths]:
        return [o for a in self.graph.nodes for b in self.graph.nodes if (o := self.between(a, b)).paths]

    def reaching(self, sources, targets):
        ids = sources.select("node_id")
        return _among(sources, reduce(DataFrame.union, [o.reaching(ids, targets.select("node_id")) for o in self._each()]))

    def reachable(self, sources, targets):
        ids = targets.select("node_id")
        return _among(targets, reduce(DataFrame.union, [o.reachable(sources.select("node_id"), ids) for o in self._each()]))

    def pairs(self, sources, targets):
        a, b = sources.select("node_id"), targets.select("node_id")
        return reduce(DataFrame.union, [o.pairs(a, b) for o in self._each()]).distinct()


class ClusterIndex(Reach):
    """Every reachable pair, clustered by the labels of its ends: an edge of a pattern reads one cluster.

    The table is as large as the closure; it is kept for the local semi-joins
    that are compared with.  Of a graph whose kinds lie on no cycle the clusters
    are made along paths of kinds when they are read, and nothing is stored.
    """

    def __init__(self, table: DataFrame, clusters: dict[tuple[str, str], DataFrame] | None = None):
        #: (source, target, src, dst)
        self.table = table
        #: (src, dst) by labels, where clusters are made apart
        self.clusters = clusters

    @classmethod
    def of_kinds(cls, graph: PropertyGraph) -> ClusterIndex:
        """The clusters by the kinds of their ends."""
        clusters = {}
        for source in graph.nodes:
            for target in graph.nodes:
                paths = graph.kind_paths(source, target)
                if paths is None:
                    raise ValueError("kinds on a cycle")
                if paths:
                    clusters[source, target] = KindPaths(paths).pairs(graph.nodes[source], graph.nodes[target]).distinct()
        wide = [rows.select(F.lit(a).alias("source"), F.lit(b).alias("target"), *[F.col(c).cast("decimal(38,0)").alias(c) for c in ("src", "dst")]) for (a, b), rows in clusters.items()]
        return cls(reduce(DataFrame.union, wide), clusters)

    @classmethod
    def build(cls, labelled: DataFrame, edges: DataFrame) -> ClusterIndex:
        """``labelled``: (node_id, label)."""
        a = labelled.select(F.col("node_id").alias("src"), F.col("label").alias("source"))
        b = labelled.select(F.col("node_id").alias("dst"), F.col("label").alias("target"))
        return cls(closure(edges).join(a, "src").join(b, "dst").select("source", "target", "src", "dst"))

    def save(self, folder: str) -> None:
        """One folder for each pair of labels, so that a cluster is read alone."""
        self.table.repartition("source", "target", F.pmod(F.xxhash64("src"), F.lit(64))).write.mode("overwrite").partitionBy("source", "target").parquet(folder)

    @classmethod
    def load(cls, spark, folder: str) -> ClusterIndex:
        return cls(spark.read.parquet(folder).select("source", "target", "src", "dst"))

    def of(self, source: str | None, target: str | None) -> Children:
        """The cluster of two labels (None: any)."""
        if self.clusters and (source, target) in self.clusters:
            return Children(self.clusters[source, target])
        table = self.table
        if source is not None:
            table = table.filter(F.col("source") == source)
        if target is not None:
            table = table.filter(F.col("target") == target)
        return Children(table.select("src", "dst"))

    def sizes(self) -> DataFrame:
        """(source, target, pairs)"""
        if self.clusters:
            return reduce(DataFrame.union, [rows.agg(F.count("*").alias("pairs")).filter("pairs > 0").select(F.lit(a).alias("source"), F.lit(b).alias("target"), "pairs") for (a, b), rows in self.clusters.items()])
        return self.table.groupBy("source", "target").agg(F.count("*").alias("pairs"))

    def reaching(self, sources, targets):
        return self.of(None, None).reaching(sources, targets)

    def reachable(self, sources, targets):
        return self.of(None, None).reachable(sources, targets)

    def pairs(self, sources, targets):
        return self.of(None, None).pairs(sources, targets)
