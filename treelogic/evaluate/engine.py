"""The contour pipeline.

1. Candidates of every pattern node by kind and attributes, with the ids that
   their rows hold of neighbours.
2. Downward round, leaves first: a candidate stays if its formula holds; the
   flags of a parent's children come from one tagged aggregation, those of leaf
   children of one kind from one scan.
3. Core: the backbone paths from the root to the outputs.
4. Upward round, root first: a core candidate stays if a candidate of its parent
   reaches it; children that the same index serves are tested together.
5. Trimming: core nodes with a single candidate are constants; what they held
   together falls into components, whose product is the answer.
6. Match graph: the pairs of each core edge, each node and edge once.  Edges that
   rows hold themselves are not made as tables unless they are asked for.
7. Enumeration from the leaves of the core by joins, dropping what is no output
   as soon as its edge is joined.

Sets that later steps read several times are written and counted (the counts are
all that reaches the driver, besides single candidates' ids); a counted set is
broadcast if it is small enough.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.graph.model import EdgeSet, PropertyGraph
from treelogic.index.reach import Children, KindPaths, Reach, Reflexive, children_of, choose
from treelogic.plans import BROADCAST_ROWS, apart, cut, small
from treelogic.query.logic import FALSE, TRUE, And, Formula, Var, simplify, to_column
from treelogic.query.pattern import PatternNode, TreePattern


@dataclass
class Options:
    """Switches of the pipeline; every setting gives the same answers."""

    index: Reach | None = None
    #: use the index for every ancestor-descendant edge, also where paths of kinds would do
    force_index: bool = False
    ad_mode: str = "strict"
    pc_mode: str = "exact"
    #: the upward round; None: always, but with ``key_joins`` only where joining an edge can multiply rows
    prune_up: bool | None = None
    #: where all edges are foreign keys, leave the core's edges to the enumeration's joins, without either round
    key_joins: bool = False
    shrink: bool = True
    #: constants and components; None: by the counts that are known anyway, True: all core nodes are counted
    trim: bool | None = None
    minimize: bool = False
    #: write the sets between the steps; None: those that several later steps read
    checkpoints: bool | None = None
    #: leave out the ids of nodes that no join needs; measures that count nodes want them
    lean: bool = False


@dataclass
class EvalResult:
    df: DataFrame
    metrics: dict = field(default_factory=dict)
    candidates: dict[str, DataFrame] = field(default_factory=dict)
    match_graph: dict[tuple[str, str], DataFrame] = field(default_factory=dict)


def atom_column(df: DataFrame, node: PatternNode):
    """The attribute predicate as a filter's or a case's condition, where null is as good as false: so a
    comparison with a missing attribute does not hold, and plain comparisons reach the scan."""
    test = F.lit(True)
    for a in node.atoms:
        if a.attribute not in df.columns:
            return F.lit(False)
        c, v = F.col(f"`{a.attribute}`"), F.lit(a.constant)
        test = test & {"<": c < v, "<=": c <= v, "=": c == v, "!=": c != v, ">": c > v, ">=": c >= v}[a.operation]
    return test


def candidates(graph: PropertyGraph, node: PatternNode, columns: Iterable[str] = ("node_id",)) -> DataFrame:
    """``node_id`` (or the named columns) of the data nodes that pass a pattern node's tests; filters reach the scan."""
    kinds = [node.kind] if node.kind else list(graph.nodes)
    parts = []
    for kind in kinds:
        rows = graph.nodes[kind]
        if all(a.attribute in rows.columns for a in node.atoms):
            parts.append((rows.filter(atom_column(rows, node)) if node.atoms else rows).select(*columns))
    if not parts:
        return graph.nodes[kinds[0]].select(*columns).limit(0)
    return reduce(DataFrame.union, parts)


def candidates_all(graph: PropertyGraph, pattern: TreePattern) -> DataFrame:
    """(qnode, kind, node_id) for all pattern nodes: each node table is read once, rows carry the names they match."""
    parts = []
    for kind, rows in graph.nodes.items():
        tests = [F.when(atom_column(rows, u), F.lit(u.name)) for u in pattern.root.walk() if u.kind in (None, kind)]
        if tests:
            parts.append(rows.select(F.explode(F.array_compact(F.array(*tests))).alias("qnode"), F.lit(kind).alias("kind"), "node_id"))
    return reduce(DataFrame.union, parts)


class Pipeline:
    """One evaluation; the rounds are methods so that measures can run them alone."""

    def __init__(self, graph: PropertyGraph, pattern: TreePattern, options: Options | None = None):
        self.graph, self.pattern, self.options = graph, pattern, options or Options()
        self.operators: dict[str, Reach] = {}
        self.exact: dict[str, Reach] = {}
        for u in pattern.root.walk():
            if pattern.parent[u.name]:
                self._bind(pattern.nodes[pattern.parent[u.name]], u)
        plain = all(isinstance(o, KindPaths | Children) for o in self.operators.values()) and pattern.size() <= 8
        keyed = self.options.key_joins and plain and all(e.keyed for o in self.operators.values() for e in (getattr(o, "sets", None) or [x for path in getattr(o, "paths", []) for x in path]))
        self.upward = self.options.prune_up if self.options.prune_up is not None else not keyed
        #: along keys the enumeration's own joins do the work of both rounds for the core's edges
        self.direct = keyed and self.options.prune_up is None and not self.exact
        self.cuts = self.options.checkpoints if self.options.checkpoints is not None else not self.direct
        #: rows of the sets that were written, by round and pattern node
        self.counts: dict[tuple[str, str], int] = {}

    def _bind(self, up: PatternNode, u: PatternNode) -> None:
        """Chooses the operator of the edge above u."""
        o = self.options
        direct = children_of(self.graph, up.kind, u.kind)
        relaxed = u.edge == "pc" and o.pc_mode == "relax" and u.backbone and not u.optional
        if u.edge == "pc" and not relaxed:
            self.operators[u.name] = direct
            return
        ad = choose(self.graph, up.kind, u.kind, o.index, o.force_index)
        if o.ad_mode == "reflexive" and u.edge == "ad":
            ad = Reflexive(ad)
        self.operators[u.name] = ad
        if relaxed:  # treated as a path while pruning, checked in the match graph
            self.exact[u.name] = direct

    def link(self, name: str) -> EdgeSet | None:
        """The edge set above a pattern node, if rows of one end hold the other's id."""
        o = self.operators.get(name)
        return o.link() if isinstance(o, KindPaths) and name not in self.exact else None

    def _kept(self, rounds: str, name: str, df: DataFrame) -> DataFrame:
        """A set of a round, written and counted if several later steps read it."""
        u = self.pattern.nodes[name]
        core = any(c.backbone for c in u.children)
        again = core if self.options.checkpoints is None else self.cuts
        if not (self.cuts and again):
            return df
        if rounds == "up" and self.options.checkpoints is None and self.counts.get(("down", name), BROADCAST_ROWS + 1) <= BROADCAST_ROWS:
            return F.broadcast(df)  # part of a small set that is written already
        df = cut(df)
        n = self.counts[rounds, name] = df.count()
        return F.broadcast(df) if n <= BROADCAST_ROWS else df

    # rounds

    def columns(self, u: PatternNode) -> list[str]:
        """What a candidate of u carries: its id, where a join needs it, and the ids that its row holds of neighbours."""
        if u.kind is None:
            return ["node_id"]
        held: set[str] = set()
        above = self.operators.get(u.name)
        if above is not None:
            held |= above.columns("target")
        for c in u.children:
            held |= self.operators[c.name].columns("source")
        held &= set(self.graph.nodes[u.kind].columns)
        if self.options.lean and not self.exact and not u.output and above is not None and not u.optional:
            link = self.link(u.name)
            links = [self.link(c.name) for c in u.children]
            inner = all(e is not None and e.holder == "source" and not c.optional for c, e in zip(u.children, links))
            if link is not None and link.holder == "target" and inner and _conjuncts(self.pattern.extended(u.name)) is not None:
                return sorted(held)
        return ["node_id", *sorted(held)]

    def candidates(self) -> dict[str, DataFrame]:
        return {u.name: candidates(self.graph, u, self.columns(u)) for u in self.pattern.root.walk()}

    def prune_down(self, cand: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """Candidates that satisfy the whole sub-pattern below their pattern node.

        With ``key_joins``, edges of the core are left to the enumeration.
        """
        cand = self._narrowed(cand) if self.options.lean else cand
        down: dict[str, DataFrame] = {}
        later = {n: TRUE for n in self.core()} if self.direct else {}
        for u in self.pattern.postorder():
            formula = simplify(self.pattern.extended(u.name).substitute(later))
            asked = [c for c in u.children if c.name in formula.variables()]
            if formula == FALSE:
                down[u.name] = cand[u.name].limit(0)
            elif not asked:
                down[u.name] = cand[u.name]
            else:
                if _conjuncts(formula) is not None:  # each child is a semi-join
                    rows = cand[u.name]
                    for c in asked:
                        rows = self.operators[c.name].reaching(rows, down[c.name])
                else:
                    flags = self._flags(cand[u.name], asked, down)
                    test = to_column(formula, lambda name: F.coalesce(F.col(f"f_{name}"), F.lit(False)))
                    # a formula that is false without any child needs no rows without flags
                    needs = simplify(formula.substitute({c.name: FALSE for c in asked})) == FALSE
                    rows = cand[u.name].join(flags, "node_id", "inner" if needs else "left").filter(test).select(*cand[u.name].columns)
                down[u.name] = self._kept("down", u.name, rows)
        return down

    def _narrowed(self, cand: dict[str, DataFrame]) -> dict[str, DataFrame]:
        """Untested children by an edge table, cut down to those below their parents' candidates: no others are asked for."""
        cand, few = dict(cand), {u.name for u in self.pattern.root.walk() if u.atoms}
        for u in self.pattern.root.walk():
            up, o = self.pattern.parent[u.name], self.operators.get(u.name)
            if u.edge == "pc" and type(o) is Children and u.name not in few and up in few:
                below = cut(o.edges.join(small(cand[up].select(F.col("node_id").alias("src"))), "src", "left_semi").select(F.col("dst").alias("node_id")).distinct())
                cand[u.name] = cut(cand[u.name].join(small(below), "node_id", "left_semi").select(*cand[u.name].columns))
                few.add(u.name)
        return cand

    def _flags(self, rows: DataFrame, asked: list[PatternNode], down: dict[str, DataFrame]) -> DataFrame:
        """One row for each node with a child: which children it reaches.  Leaf children of one kind whose rows
        hold the parent's id share one scan; the others are tagged and collected by one aggregation."""
        together: dict[str, list[PatternNode]] = {}
        for c in asked:
            link = self.link(c.name)
            if link is not None and link.holder == "target" and not c.children and c.kind:
                together.setdefault(link.name, []).append(c)
        parts = []
        names = [c.name for c in asked]
        for kids in together.values():
            nodes, link = self.graph.nodes[kids[0].kind], self.link(kids[0].name)
            tests = {c.name: atom_column(nodes, c) for c in kids}
            some = nodes.filter(reduce(lambda a, b: a | b, tests.values()))
            parts.append(some.select(F.col(link.column).alias("node_id"), *[tests.get(n, F.lit(False)).alias(f"f_{n}") for n in names]))
        apart = [c for c in asked if not any(c in kids for kids in together.values())]
        for c in apart:
            hit = self.operators[c.name].reaching(rows, down[c.name])
            parts.append(hit.select("node_id", *[F.lit(n == c.name).alias(f"f_{n}") for n in names]))
        return reduce(DataFrame.union, parts).groupBy("node_id").agg(*[F.max(f"f_{n}").alias(f"f_{n}") for n in names])

    def core(self) -> list[str]:
        """Names of the core in root-first order: backbone paths to the outputs; without ``shrink`` the whole backbone."""
        backbone = self.pattern.backbone()
        if not self.options.shrink:
            return backbone
        wanted = set()
        for name in self.pattern.outputs():
            wanted |= set(self.pattern.path(name))
        # relaxed edges must be checked in the match graph whether or not they lead to an output
        for name in self.exact:
            wanted |= set(self.pattern.path(name))
        return [n for n in backbone if n in wanted] or [self.pattern.root.name]

    def prune_up(self, down: dict[str, DataFrame], core: list[str]) -> dict[str, DataFrame]:
        """Core candidates that a surviving candidate of their parent reaches; every parent is used, single ones too."""
        up = dict(down)
        for parent in core:
            below = [c.name for c in self.pattern.children(parent, True) if c.name in core and not c.optional]
            groups: dict[int, list[str]] = {}
            for name in below:
                o = self.operators[name]
                groups.setdefault(id(o) if o is self.options.index else hash(name), []).append(name)
            for names in groups.values():
                o = self.operators[names[0]]
                if len(names) == 1:
                    found = {names[0]: o.reachable(up[parent], down[names[0]])}
                else:  # one test for the nodes of all of them
                    found = merged_reachable(o, up[parent], {n: down[n] for n in names})
                for name, df in found.items():
                    up[name] = self._kept("up", name, df)
        return up

    def singles(self, up: dict[str, DataFrame], core: list[str]) -> dict[str, object]:
        """Core nodes with one candidate, and its id: by known counts, or by one action over all of the core.
        A node above an optional one is not among them: nothing has tested the optional node's candidates yet."""
        free = {n for n in core if self.pattern.nodes[n].optional}
        above = {self.pattern.parent[n] for n in free}
        able = [n for n in core if "node_id" in up[n].columns and n not in free and n not in above]
        last = {n: self.counts.get(("up", n), self.counts.get(("down", n))) for n in able}
        if self.options.trim is None:
            able = [n for n in able if last[n] == 1]
        elif self.options.trim:
            able = [n for n in able if last[n] in (None, 1)]
        else:
            return {}
        if not able:
            return {}
        few = reduce(DataFrame.union, [up[n].select("node_id").distinct().limit(2).select(F.lit(n).alias("qnode"), F.col("node_id").cast("decimal(38,0)").alias("node_id")) for n in able])
        ids: dict[str, list] = {}
        for r in few.collect():
            ids.setdefault(r["qnode"], []).append(r["node_id"])
        return {n: F.lit(v[0]).cast(up[n].schema["node_id"].dataType) for n, v in ids.items() if len(v) == 1}

    def edges(self, cand: dict[str, DataFrame], core: list[str], skip: Iterable[str] = ()) -> dict[tuple[str, str], DataFrame]:
        """Match graph: (src, dst) of each core edge, but for those above the nodes in ``skip``."""
        out = {}
        for name in core:
            parent = self.pattern.parent[name]
            if parent is not None and name not in skip:
                exact = self.exact.get(name)
                pairs = (exact or self.operators[name]).pairs(cand[parent], cand[name])
                out[parent, name] = cut(pairs) if self.exact or self.options.checkpoints else pairs
        return self._cascade(out, cand) if self.exact else out

    def _cascade(self, edges: dict, cand: dict[str, DataFrame]) -> dict:
        """After relaxed edges were checked: drops edges whose ends have lost what they need, until stable."""
        names = list(edges)
        while True:
            before = {k: edges[k].count() for k in names}
            for up, name in names:
                e = edges[up, name]
                for below in [k for k in names if k[0] == name and not self.pattern.nodes[k[1]].optional]:
                    e = e.join(edges[below].select(F.col("src").alias("dst")).distinct(), "dst", "left_semi")
                above = self.pattern.parent[up]
                if above is not None:
                    e = e.join(edges[above, up].select(F.col("dst").alias("src")).distinct(), "src", "left_semi")
                for other in [k for k in names if k[0] == up and k != (up, name) and not self.pattern.nodes[k[1]].optional]:
                    e = e.join(edges[other].select("src").distinct(), "src", "left_semi")
                edges[up, name] = cut(e.select("src", "dst"))
            if {k: edges[k].count() for k in names} == before:
                return edges

    def enumerate(self, cand: dict[str, DataFrame], edges: dict[tuple[str, str], DataFrame], core: list[str], single: dict[str, object] | None = None) -> DataFrame:
        """Output tuples (one column of node ids for each output), each once."""
        single = single or {}
        outputs = self.pattern.outputs()
        if not outputs:
            return self.graph.spark.createDataFrame([(not cand[self.pattern.root.name].isEmpty(),)], "answer boolean")
        # ancestors above the outputs' lowest common ancestor only have to exist; constants cut the rest apart
        start = self._top(core)
        inside = [n for n in core if start in self.pattern.path(n)]
        tops = [n for n in inside if n not in single and (n == start or self.pattern.parent[n] in single)]
        out = None
        for top in tops:
            part = self._component(top, cand, edges, [n for n in inside if n not in single])
            if part is not None:
                out = part if out is None else out.crossJoin(part)
        if out is None:
            out = self.graph.spark.range(1)
        for name in outputs:
            if name in single:
                out = out.withColumn(name, single[name])
        return out.select(*outputs).distinct()

    def _component(self, top: str, cand: dict[str, DataFrame], edges: dict[tuple[str, str], DataFrame], core: list[str]) -> DataFrame | None:
        """Tuples of the outputs at and below a core node; None if there are none."""
        pattern = self.pattern

        def below(name: str) -> list[PatternNode]:
            return sorted([c for c in pattern.children(name, True) if c.name in core], key=lambda c: c.optional)

        def outputs(name: str) -> list[str]:
            return [n for n in pattern.outputs() if n in core and name in pattern.path(n)]

        def rows(name: str) -> DataFrame:
            """Outputs at and below the node, with ``__key``: what its parent joins on."""
            u, link = pattern.nodes[name], self.link(name) if name != top else None
            held = link.column if link is not None and link.held_by("target", cand[name]) else None
            out, kids = cand[name], below(name)
            # edges above the children: held by this node's row, by the child's rows, or a table
            wants = set()
            for c in kids:
                l = self.link(c.name)
                wants.add(l.column if l is not None and l.held_by("source", out) else "node_id")
            if u.output or held is None and name != top:
                wants.add("node_id")
            if held:
                wants.add(held)
            out = out.select(*[F.col(w).alias(f"__{w}") for w in sorted(wants)]) if wants else out
            for c in kids:
                l = self.link(c.name)
                at = f"__{l.column}" if l is not None and l.held_by("source", cand[name]) else "__node_id"
                part = rows(c.name)
                if (name, c.name) in edges:
                    part = edges[name, c.name].select(F.col("src").alias(at), F.col("dst").alias("__key")).join(part, "__key").drop("__key")
                else:
                    part = part.withColumnRenamed("__key", at)
                out = out.join(part, at, "left" if c.optional else "inner")
            columns = [F.col(f"__{held}" if held else "__node_id").alias("__key")] if name != top else []
            columns += [F.col("__node_id").alias(n) if n == name else F.col(n) for n in outputs(name)]
            out = out.select(*columns)
            # where the node itself is no output its tuples may repeat
            return out if u.output and not kids else out.distinct()

        return rows(top).select(*outputs(top)) if outputs(top) else None

    def _streams(self, core: list[str]) -> bool:
        """Whether the answers can be made row by row: all of the core are outputs, so that no tuple comes twice, and
        first places stand for an edge's pairs."""
        o = self.options
        plain = o.lean and o.checkpoints is None and not self.exact and self.upward and not any(self.pattern.nodes[n].optional for n in core)
        return plain and set(core) == set(self.pattern.outputs()) and any(getattr(self.operators.get(n), "summed", None) is not None for n in core)

    def _streamed(self, cand: dict[str, DataFrame], core: list[str]) -> DataFrame:
        """Output tuples from the root on: each edge multiplies the rows at hand by a look-up in its own (small) tables,
        so that neither tuples nor pairs are shuffled or written."""
        out = cut(cand[core[0]].select(F.col("node_id").alias(core[0])).distinct())
        # few rows at first, of which each may become very many
        out = out.repartition(4 * max(self.graph.spark.sparkContext.defaultParallelism, int(self.graph.spark.conf.get("spark.sql.shuffle.partitions"))))
        for name in core[1:]:
            up = self.pattern.parent[name]
            out = self.operators[name].walked(apart(out), up, name, cand[up], cand[name])
        return out.select(*self.pattern.outputs())

    def _top(self, core: list[str]) -> str:
        """The lowest core node above all outputs (the root without ``shrink``)."""
        outputs = self.pattern.outputs()
        if not self.options.shrink or not self.upward or not outputs or self.exact:
            return self.pattern.root.name
        common = None
        for name in outputs:
            path = self.pattern.path(name)
            common = path if common is None else [a for a, b in zip(common, path) if a == b]
        return common[-1]

    def rounds(self) -> tuple[dict, dict, dict, list[str]]:
        """(candidates, after the downward round, after the upward round, core)."""
        cand = self.candidates()
        down = self.prune_down(cand)
        core = self.core()
        return cand, down, self.prune_up(down, core) if self.upward else down, core

    def answer(self, up: dict[str, DataFrame], core: list[str]) -> tuple[DataFrame, dict]:
        """(tuples, match graph as far as the enumeration needs its tables)."""
        if self.exact:
            edges = self.edges(up, core)
            for (a, b), e in edges.items():
                up[b] = up[b].join(e.select(F.col("dst").alias("node_id")).distinct(), "node_id", "left_semi")
                up[a] = up[a].join(e.select(F.col("src").alias("node_id")).distinct(), "node_id", "left_semi") if not self.pattern.nodes[b].optional else up[a]
            return self.enumerate(up, edges, core), edges
        if self._streams(core):
            return self._streamed(up, core), {}
        held = {n for n in core if (l := self.link(n)) is not None and (l.held_by("target", up[n]) or l.held_by("source", up[self.pattern.parent[n]]))}
        single = self.singles(up, core) if self.upward and self.options.shrink else {}
        edges = self.edges(up, core, held if self.options.lean else {n for n in held if n not in core})
        return self.enumerate(up, {k: e for k, e in edges.items() if k[1] not in held}, core, single), edges

    def run(self) -> EvalResult:
        cand, down, up, core = self.rounds()
        df, edges = self.answer(up, core)
        return EvalResult(df, {"core": core, "counts": self.counts}, {"cand": cand, "down": down, "up": up}, edges)


def _conjuncts(formula: Formula) -> set[str] | None:
    """The variables of a formula that asks for all of them and nothing else; None for others."""
    only = simplify(formula)
    if only == TRUE:
        return set()
    if isinstance(only, Var) or isinstance(only, And) and all(isinstance(i, Var) for i in only.items):
        return only.variables()
    return None


def merged_reachable(operator: Reach, sources: DataFrame, targets: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """``reachable`` for several sets of targets at once: a node that several of them hold is tested once."""
    tagged = reduce(DataFrame.union, [df.select("node_id", F.lit(n).alias("qnode")) for n, df in targets.items()])
    nodes = tagged.groupBy("node_id").agg(F.collect_set("qnode").alias("qnodes"))
    found = cut(operator.reachable(sources, nodes).select("node_id", "qnodes"))
    return {n: _among_of(df, found.filter(F.array_contains("qnodes", n))) for n, df in targets.items()}


def _among_of(rows: DataFrame, found: DataFrame) -> DataFrame:
    if rows.columns == ["node_id"]:
        return found.select("node_id")
    return rows.join(found.select("node_id"), "node_id", "left_semi").select(*rows.columns)


def evaluate(graph: PropertyGraph, pattern: TreePattern, project: dict[str, list[str]] | None = None, **options) -> EvalResult:
    """Answers of a pattern.

    Columns are the outputs' node ids or, with ``project`` (output -> attribute
    columns), the attributes, named as given, as a distinct table.  A pattern
    that cannot be satisfied gives an empty table without a job.
    """
    from treelogic.analysis.minimize import minimize
    from treelogic.analysis.satisfy import satisfiable

    o = Options(**({"lean": True} | options))
    if not satisfiable(pattern):
        empty = graph.spark.createDataFrame([], ", ".join(f"{n} {id_type(graph, pattern.nodes[n].kind)}" for n in pattern.outputs()) or "answer boolean")
        return EvalResult(projected(graph, pattern, empty, project) if project else empty, {"satisfiable": False})
    if o.minimize:
        pattern = minimize(pattern)[0]
    result = Pipeline(graph, pattern, o).run()
    if project:
        result.df = projected(graph, pattern, result.df, project)
    return result


def id_type(graph: PropertyGraph, kind: str | None) -> str:
    """Spark's name of the type of a kind's ids."""
    kinds = [kind] if kind else list(graph.nodes)
    types = {graph.nodes[k].schema["node_id"].dataType.simpleString() for k in kinds}
    return types.pop() if len(types) == 1 else "decimal(38,0)"


def projected(graph: PropertyGraph, pattern: TreePattern, rows: DataFrame, project: dict[str, list[str]]) -> DataFrame:
    """Replaces node ids by attributes.

    What a node's id tells is read off it; other attributes are joined late, so
    that they are never shuffled before.  An output without a kind has the
    attributes of any kind; those that its node's kind lacks are null.
    """
    columns = []
    for name, attributes in project.items():
        node = pattern.nodes[name]
        named = [a if isinstance(a, tuple) else (a, a) for a in attributes]
        known = graph.keys.get(node.kind, {})
        if all(a in known for a, _ in named):
            rows = rows.select("*", *[known[a](F.col(name)).alias(n) for a, n in named])
        else:
            parts = []
            for kind in [node.kind] if node.kind else graph.nodes:
                table = graph.nodes[kind]
                if any(a in table.columns for a, _ in named) or node.kind:
                    parts.append(table.select(F.col("node_id").alias(name), *[(F.col(a) if a in table.columns or node.kind else F.lit(None)).alias(n) for a, n in named]))
                else:
                    parts.append(table.select(F.col("node_id").alias(name), *[F.lit(None).alias(n) for _, n in named]))
            rows = rows.join(reduce(DataFrame.union, parts), name, "left" if node.optional else "inner")
        columns += [n for _, n in named]
    return rows.select(*columns).distinct()


def explain(graph: PropertyGraph, pattern: TreePattern, **options) -> str:
    """What would be done, in words: fragment, polarities, rewrites, operators, core."""
    from treelogic.analysis.minimize import minimize
    from treelogic.analysis.satisfy import satisfiable

    if not satisfiable(pattern):
        return f"{pattern}\nno graph has an answer: empty result, no job"
    small, trace = minimize(pattern)
    p = Pipeline(graph, pattern, Options(**options))
    lines = [str(pattern), f"fragment: {pattern.fragment()}; {pattern.size()} nodes, {small.size()} after {trace or 'no rewrite'}"]
    lines += [f"{n}: asked for {'/'.join(sorted('true' if s else 'false' for s in pattern.polarity(n)))}, by {type(o).__name__}" + (f" of {len(o.paths)} paths" if isinstance(o, KindPaths) else "") + (f", ids held by the {link.holder}" if (link := p.link(n)) else "") for n, o in p.operators.items()]
    core = p.core()
    return "\n".join([*lines, f"core: {', '.join(core)}; enumeration from {p._top(core)}; upward round: {p.upward}; sets written: {p.cuts}"])


def count_matches(graph: PropertyGraph, pattern: TreePattern, **options) -> int:
    """Number of answers without enumerating them, where every core node is an output: sums of
    products of counts up the match graph, whose pairs a complete chain index does not make.  Other patterns are enumerated."""
    p = Pipeline(graph, pattern, Options(**options))
    core = p.core()
    if any(not pattern.nodes[n].output for n in core) or any(pattern.nodes[n].optional for n in core):
        return p.run().df.count()
    _, _, up, _ = p.rounds()
    up = {n: up[n].dropDuplicates(["node_id"]) for n in core}  # a node counts once, however often its row is there
    edges = {k: e.distinct() for k, e in p.edges(up, core).items()} if p.exact else {}

    def below(name: str, child: str) -> DataFrame:
        """(node_id, m): the ways below a node by one of its children."""
        if not edges:
            return p.operators[child].weighed(up[name], ways(child))
        return edges[name, child].join(ways(child).withColumnRenamed("node_id", "dst"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.sum("n").alias("m"))

    def ways(name: str) -> DataFrame:
        out = None
        for c in pattern.children(name, True):
            if c.name in core:
                part = below(name, c.name)
                out = part.withColumnRenamed("m", "n") if out is None else out.join(part, "node_id").select("node_id", (F.col("n") * F.col("m")).alias("n"))
        return up[name].select("node_id", F.lit(1).cast("decimal(38,0)").alias("n")) if out is None else out

    return int(ways(pattern.root.name).agg(F.sum("n")).first()[0] or 0)


def group_matches(graph: PropertyGraph, pattern: TreePattern, group: str, **options) -> DataFrame:
    """The group operator: (group node, set of the tuples of the other outputs)."""
    rows = evaluate(graph, pattern, **options).df
    others = [c for c in rows.columns if c != group]
    return rows.groupBy(group).agg(F.collect_set(F.struct(*others)).alias("matches"))


def nested_matches(graph: PropertyGraph, pattern: TreePattern, groups: Iterable[str], **options) -> DataFrame:
    """Group elements inside group elements: for each group node u, lowest first, the outputs below u are
    gathered into ``<u>_matches``, the set of their tuples for one tuple of the other columns.

    A group with no output below it is an error.  One group's set is one value, so
    groups are for results that a row can hold.
    """
    rows = evaluate(graph, pattern, **options).df
    for u in sorted(groups, key=lambda u: -len(pattern.path(u))):
        below = [n.name for n in pattern.nodes[u].walk()][1:]
        inner = [c for c in rows.columns if c in below or c.endswith("_matches") and c.removesuffix("_matches") in below]
        if not inner:
            raise ValueError(f"no output below {u}")
        rows = rows.groupBy(*[c for c in rows.columns if c not in inner]).agg(F.collect_set(F.struct(*inner)).alias(f"{u}_matches"))
    return rows


def evaluate_combinations(graph: PropertyGraph, pattern: TreePattern, names: Iterable[str], **options) -> DataFrame:
    """The outputs and the images of predicate nodes where these hold: all combinations of true nodes.

    Each named node, a predicate child of a backbone node, is asked for a second
    time as an optional output, while the first stays in the formula.  Its column is
    null where the node is false; ``present`` lists the names that are true.
    """
    names = list(names)
    for n in names:
        if pattern.nodes[n].backbone or not pattern.nodes[pattern.parent[n]].backbone:
            raise ValueError(f"{n} is no predicate child of a backbone node")
    shown = {n: f"{n}__shown" for n in names}

    def twin(n: PatternNode, top: bool) -> PatternNode:
        mark = {c.name: Var(f"{c.name}__shown") for c in n.children}
        return replace(n, name=f"{n.name}__shown", backbone=top, output=top, optional=top, formula=n.formula.substitute(mark), children=tuple(twin(c, False) for c in n.children))

    def add(n: PatternNode) -> PatternNode:
        return replace(n, children=(*n.children, *(twin(pattern.nodes[c.name], True) for c in n.children if c.name in shown)))

    rows = evaluate(graph, pattern.map(add), **options).df
    for n, s in shown.items():
        rows = rows.withColumnRenamed(s, n)
    present = F.array_compact(F.array(*[F.when(F.col(n).isNotNull(), F.lit(n)) for n in names]))
    return rows.withColumn("present", present)


def evaluate_multi(graph: PropertyGraph, pattern: TreePattern, output_sets: dict[str, list[str]], **options) -> dict[str, DataFrame]:
    """One table for each named set of outputs.  The rounds run once, for the core of all of them;
    each set is then enumerated on its own core."""
    every = pattern.with_outputs([n for names in output_sets.values() for n in names])
    whole = Pipeline(graph, every, Options(**options))
    _, _, up, _ = whole.rounds()
    out = {}
    for name, outputs in output_sets.items():
        p = Pipeline(graph, pattern.with_outputs(outputs), replace(whole.options, lean=False))
        p.counts = dict(whole.counts)
        out[name] = p.answer(dict(up), p.core())[0]
    return out


def evaluate_present(graph: PropertyGraph, pattern: TreePattern, **options) -> DataFrame:
    """The outputs, and for each predicate child of the root whether it holds (``has_<child>``): all
    combinations of true predicate nodes that the root's formula allows."""
    p = Pipeline(graph, pattern, Options(**options))
    cand, down, up, core = p.rounds()
    rows, _ = p.answer(up, core)
    root = pattern.root
    if not root.output:
        raise ValueError("the root must be an output")
    for c in root.children:
        if not c.backbone:
            hit = p.operators[c.name].reaching(up[root.name], down[c.name]).select(F.col("node_id").alias(root.name)).distinct()
            rows = rows.join(hit.withColumn(f"has_{c.name}", F.lit(True)), root.name, "left").withColumn(f"has_{c.name}", F.coalesce(f"has_{c.name}", F.lit(False)))
    return rows
