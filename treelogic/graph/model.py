"""Property graphs: node tables by kind and edge tables between kinds.

Every node table has ``node_id`` (unique over the whole graph) and one typed
column for each attribute, so that attribute tests reach the Parquet scan.
"""

from __future__ import annotations

from collections.abc import Callable, Mapping
from dataclasses import dataclass, field
from decimal import Decimal
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KEY_BITS = 56


@dataclass(frozen=True)
class EdgeSet:
    """Edges ``df(src, dst)`` from one kind to another; ``role`` is tree or ref.

    ``keyed``: one of the ends determines the other (a foreign key), so that a
    join along the edges cannot multiply both sides.  ``holder`` (source or
    target) and ``column``: the node table of that end has the other end's id in
    that column, so rows that carry it need no join with the edge table.  ``rows``
    is that node table.
    """

    name: str
    source: str
    target: str
    role: str
    df: DataFrame
    keyed: bool = False
    holder: str | None = None
    column: str | None = None
    rows: DataFrame | None = None

    def held_by(self, end: str, rows: DataFrame) -> bool:
        """Whether these rows of one end carry the other end's id."""
        return self.holder == end and self.column in rows.columns

    def back(self, targets: DataFrame) -> DataFrame:
        """``node_id`` of the sources of edges to the targets, with repeats."""
        if self.held_by("target", targets):
            return targets.select(F.col(self.column).alias("node_id"))
        return self.df.join(targets.select(F.col("node_id").alias("dst")), "dst", "left_semi").select(F.col("src").alias("node_id"))

    def ahead(self, sources: DataFrame) -> DataFrame:
        """``node_id`` of the targets of edges from the sources, with repeats."""
        if self.held_by("source", sources):
            return sources.select(F.col(self.column).alias("node_id"))
        return self.df.join(sources.select(F.col("node_id").alias("src")), "src", "left_semi").select(F.col("dst").alias("node_id"))

    def sources_to(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """The sources (with all their columns) that have an edge to a target."""
        if self.held_by("source", sources):
            return sources.join(targets.select(F.col("node_id").alias(self.column)), self.column, "left_semi").select(*sources.columns)
        return sources.join(self.back(targets), "node_id", "left_semi").select(*sources.columns)

    def targets_from(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """The targets (with all their columns) that have an edge from a source."""
        if self.held_by("target", targets):
            return targets.join(sources.select(F.col("node_id").alias(self.column)), self.column, "left_semi").select(*targets.columns)
        return targets.join(self.ahead(sources), "node_id", "left_semi").select(*targets.columns)

    def between(self, sources: DataFrame, targets: DataFrame) -> DataFrame:
        """(src, dst) of the edges between the two sets."""
        a, b = sources.select(F.col("node_id").alias("src")), targets.select(F.col("node_id").alias("dst"))
        if self.held_by("target", targets):
            return targets.select(F.col(self.column).alias("src"), F.col("node_id").alias("dst")).join(a, "src", "left_semi").select("src", "dst")
        if self.held_by("source", sources):
            return sources.select(F.col("node_id").alias("src"), F.col(self.column).alias("dst")).join(b, "dst", "left_semi").select("src", "dst")
        return self.df.join(a, "src", "left_semi").join(b, "dst", "left_semi").select("src", "dst")


class Tables(Mapping):
    """Node tables by kind, each made when it is first asked for."""

    def __init__(self, makers: dict[str, Callable[[], DataFrame]]):
        self._makers, self._made = makers, {}

    def __getitem__(self, kind: str) -> DataFrame:
        if kind not in self._made:
            self._made[kind] = self._makers[kind]()
        return self._made[kind]

    def __iter__(self):
        return iter(self._makers)

    def __len__(self) -> int:
        return len(self._makers)


def through(path: list[EdgeSet]) -> list[EdgeSet]:
    """The path with two steps in one where a row in the middle holds both of its neighbours' ids."""
    out: list[EdgeSet] = []
    for e in path:
        last = out[-1] if out else None
        if last is not None and last.holder == "target" and e.holder == "source" and last.rows is not None and last.rows is e.rows:
            df = e.rows.select(F.col(last.column).alias("src"), F.col(e.column).alias("dst"))
            out[-1] = EdgeSet(f"{last.name}+{e.name}", last.source, e.target, "ref", df)
        else:
            out.append(e)
    return out


@dataclass
class PropertyGraph:
    nodes: Mapping[str, DataFrame]
    edges: list[EdgeSet]
    #: attributes that can be read off a node's id, by kind: {column: function of the id column}
    keys: dict[str, dict[str, Callable]] = field(default_factory=dict)
    _paths: dict = field(default_factory=dict)

    @property
    def spark(self) -> SparkSession:
        return next(iter(self.nodes.values())).sparkSession

    def all_edges(self) -> DataFrame:
        """(src, dst) of all kinds, each once."""
        return reduce(DataFrame.union, [e.df.select("src", "dst") for e in self.edges]).distinct()

    def all_nodes(self) -> DataFrame:
        return reduce(DataFrame.union, [n.select("node_id") for n in self.nodes.values()])

    def between(self, source: str | None, target: str | None) -> list[EdgeSet]:
        return [e for e in self.edges if source in (None, e.source) and target in (None, e.target)]

    def kind_paths(self, source: str, target: str, most: int = 64) -> list[list[EdgeSet]] | None:
        """All nonempty edge-set paths between two kinds; None if a cycle of kinds lies between them."""
        if (source, target) not in self._paths:
            leads = {target}
            while more := {e.source for e in self.edges if e.target in leads} - leads:
                leads |= more
            found: list[list[EdgeSet]] = []

            def go(kind: str, path: list[EdgeSet], seen: frozenset[str]) -> bool:
                for e in self.edges:
                    if e.source == kind and e.target in leads:
                        if e.target in seen or len(found) > most:
                            return False
                        if e.target == target:
                            found.append([*path, e])
                        if not go(e.target, [*path, e], seen | {e.target}):
                            return False
                return True

            self._paths[source, target] = found if go(source, [], frozenset({source})) else None
        return self._paths[source, target]


def global_id(code: int, key) -> Column:
    """Node id of a natural key of a kind: the kind's code above 56 bits of key.  Other keys are an error."""
    key = key.cast("long")
    fits = key.isNull() | ((key >= 0) & (key < F.lit(1 << KEY_BITS)))
    return F.when(fits, F.lit(code << KEY_BITS).cast("long").bitwiseOR(key)).otherwise(F.raise_error(F.lit(f"a key of kind {code} does not fit into {KEY_BITS} bits")).cast("long"))


def natural_key(column) -> Column:
    """The natural key inside a node id."""
    column = F.col(column) if isinstance(column, str) else column
    return column.bitwiseAND(F.lit((1 << KEY_BITS) - 1))


def wide_id(code: int, columns: list[str]) -> Column:
    """Node id of rows that have no key: 119 bits of hash of the whole row, above all other ids.

    At 10**12 rows two different ones share an id with a probability of about 10**-12.
    """
    high = F.xxhash64(F.lit(1), *columns).bitwiseAND(F.lit((1 << KEY_BITS) - 1)).cast("decimal(38,0)")
    low = F.xxhash64(F.lit(2), *columns).bitwiseAND(F.lit((1 << 63) - 1)).cast("decimal(38,0)")
    return (F.lit(Decimal(code << 119)).cast("decimal(38,0)") + high * F.lit(Decimal(1 << 63)).cast("decimal(38,0)") + low).cast("decimal(38,0)")


def from_rows(spark: SparkSession, nodes: list[tuple], edges: list[tuple[int, int]], schema: str = "node_id long, tag string, val int") -> PropertyGraph:
    """A graph of one kind from rows in memory."""
    return PropertyGraph({"node": spark.createDataFrame(nodes, schema)}, [EdgeSet("edge", "node", "node", "ref", spark.createDataFrame(sorted(edges), "src long, dst long"))])
