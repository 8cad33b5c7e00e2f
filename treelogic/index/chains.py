"""Chain index: a cover of the graph by chains, entry lists between them, and contours.

Nodes of a chain reach those after them.  An entry (cid, sid, to_cid, to_sid)
says that from place sid of chain cid on, place to_sid of another chain is the
first that can be reached; it is kept only where it improves on the entry of
the next place.  A set's predecessor contour holds for every chain the last
place that reaches a member, its successor contour the first place that a member
reaches; set tests compare a node's place with one row.

Contours carry two places: reflexive (members count at their own place) and
strict (a member counts one place before its own, or at its own if it lies on a
cycle), since paths of the pattern are nonempty.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treelogic.graph.model import KEY_BITS, EdgeSet, PropertyGraph
from treelogic.index.reach import KindPaths, Reach, _among
from treelogic.index.scc import condense
from treelogic.plans import apart, cut, small, stored

#: Targets of a chain that are joined as one row
RUN = 1024


def natural_chains(nodes: DataFrame, key: str, *order: str) -> DataFrame:
    """Chains that the data has: rows with the same key in their order (one window)."""
    return nodes.select("node_id", F.col(key).cast("long").alias("cid"), F.row_number().over(Window.partitionBy(key).orderBy(*order)).alias("sid"))


def greedy_chains(nodes: DataFrame, dag: DataFrame) -> DataFrame:
    """A cover by paths: each node proposes to its least free successor, which takes its least suitor.

    Rounds pair ends of paths until none is free; one path is one chain.  The
    number of rounds is that of proposals, not of nodes.
    """
    link = None  # src -> dst, each at most once on either side
    free = cut(dag)
    while not free.isEmpty():
        wish = free.groupBy("src").agg(F.min("dst").alias("dst"))
        take = wish.groupBy("dst").agg(F.min("src").alias("src")).select("src", "dst")
        link = cut(take if link is None else link.union(take))
        free = cut(free.join(link.select("src"), "src", "left_anti").join(link.select("dst"), "dst", "left_anti").select("src", "dst"))
    if link is None:
        return nodes.select("node_id", F.col("node_id").alias("cid"), F.lit(1).alias("sid"))
    link = link.join(nodes.select(F.col("node_id").alias("src")), "src", "left_semi")  # an end that is no node heads no path
    # pointer jumping to the head of each path, adding up distances
    head = cut(nodes.select("node_id").join(link.select(F.col("dst").alias("node_id"), F.col("src").alias("up")), "node_id", "left").select("node_id", F.coalesce("up", "node_id").alias("up"), F.when(F.col("up").isNull(), 0).otherwise(1).alias("far")))
    while True:
        above = head.select(F.col("node_id").alias("up"), F.col("up").alias("up2"), F.col("far").alias("far2"))
        after = cut(head.join(above, "up").select("node_id", F.col("up2").alias("up"), (F.col("far") + F.col("far2")).alias("far"), (F.col("up") != F.col("up2")).alias("moved")))
        if after.filter("moved").isEmpty():
            return after.select("node_id", F.col("up").alias("cid"), (F.col("far") + 1).cast("int").alias("sid"))
        head = after.drop("moved")


def improved(entries: DataFrame) -> DataFrame:
    """Keeps the entries that improve on every later place of their chain (delta lists)."""
    best = entries.groupBy("cid", "sid", "to_cid").agg(F.min("to_sid").alias("to_sid"))
    later = F.min("to_sid").over(Window.partitionBy("cid", "to_cid").orderBy(F.desc("sid")).rowsBetween(Window.unboundedPreceding, -1))
    return best.withColumn("later", later).filter("later is null or to_sid < later").drop("later")


def entry_lists(chains: DataFrame, dag: DataFrame, most_rounds: int = 64) -> DataFrame:
    """All entries between chains, by joining entry lists with themselves until nothing improves."""
    a = chains.select(F.col("node_id").alias("src"), "cid", "sid")
    b = chains.select(F.col("node_id").alias("dst"), F.col("cid").alias("to_cid"), F.col("sid").alias("to_sid"))
    entries = cut(improved(dag.join(a, "src").join(b, "dst").filter("cid <> to_cid").select("cid", "sid", "to_cid", "to_sid")))
    # intervals: an entry serves the places after its forerunner up to its own, so a lookup is one range match
    for _ in range(most_rounds):
        before = F.lag("sid", 1, 0).over(Window.partitionBy("cid", "to_cid").orderBy("sid"))
        served = entries.withColumn("after", before)
        second = served.select(F.col("cid").alias("to_cid"), F.col("after").alias("lo"), F.col("sid").alias("hi"), F.col("to_cid").alias("end_cid"), F.col("to_sid").alias("end_sid"))
        step = entries.join(second, "to_cid").filter("to_sid > lo and to_sid <= hi and cid <> end_cid").select("cid", "sid", F.col("end_cid").alias("to_cid"), F.col("end_sid").alias("to_sid"))
        after = cut(improved(entries.union(step)))
        if after.join(entries, ["cid", "sid", "to_cid", "to_sid"], "left_anti").isEmpty():
            return after
        entries = after
    raise RuntimeError("the entry lists did not settle")


def swept_lists(chains: DataFrame, dag: DataFrame, order: DataFrame, width: int = 16, ends: DataFrame | None = None) -> DataFrame:
    """The same entries by one pass against a topological order, for blocks of about ``width`` target chains apart.

    ``order`` has ``node_id`` and the columns whose order is topological.  A task
    reads all edges for its block, last nodes first, and holds a row of places
    for each chain and for each node that an earlier one still leads to; nothing
    is joined with itself, so the work is edges times blocks.  ``ends`` (cid)
    names the chains that entries are wanted to; None: all.
    """
    uses = dag.groupBy(F.col("dst").alias("node_id")).agg(F.count("*").alias("uses"))
    rows = order.join(chains, "node_id").join(uses, "node_id", "left").join(dag.select(F.col("src").alias("node_id"), "dst"), "node_id", "left")
    return _swept(rows, [c for c in order.columns if c != "node_id"], chains if ends is None else ends, width)


def _swept(rows: DataFrame, keys: list[str], ends: DataFrame, width: int = 16) -> DataFrame:
    """The pass over ``rows``: node_id, cid, sid, uses (edges to the node), dst (one edge from the node, or null) and the keys of
    the order.  A chain's own edges, from each place to the next, may be left out of them: the pass goes along the chains."""
    ends = cut(ends.select("cid").distinct())
    blocks = max(1, -(-ends.count() // width))
    own = F.pmod(F.xxhash64("cid"), F.lit(blocks)).cast("int")
    most = ends.groupBy(own.alias("own")).agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 1
    rows = rows.join(small(ends.withColumn("own", own)), "cid", "left")
    laid = rows.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), "own", "node_id", "cid", "sid", "uses", "dst", *keys)
    laid = laid.repartition("block").sortWithinPartitions("block", *[F.desc(c) for c in keys], F.desc("node_id")).drop(*keys)
    never = np.iinfo(np.int32).max

    def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = node = None
        found: list[tuple[int, int, int, int]] = []
        place: dict[int, np.ndarray] = {}  # chain -> first places from its node seen last
        waiting: dict[int, list] = {}      # node -> [edges to it that are still to come, its first places]
        column: dict[int, int] = {}
        names: list[int] = []

        def settle() -> None:
            """Entries of the node at hand: where it gets further than the next place of its chain."""
            if node is None:
                return
            _, here, own, cid, sid, uses = node
            before = place.get(cid)
            for i in np.flatnonzero(here < (never if before is None else before)):
                if names[i] != cid:
                    found.append((cid, sid, names[i], int(here[i])))
            if own == block:
                if cid not in column:
                    column[cid] = len(names)
                    names.append(cid)
                here[column[cid]] = sid
            place[cid] = here
            if uses:
                waiting[node[0]] = [uses, here]

        def out() -> pa.RecordBatch:
            columns = list(zip(*found)) or [(), (), (), ()]
            found.clear()
            return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int32()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.int32())], names=["cid", "sid", "to_cid", "to_sid"])

        for batch in batches:
            for b, own, node_id, cid, sid, uses, dst in zip(*(c.to_pylist() for c in batch.columns)):
                if b != block or node is None or node_id != node[0]:
                    settle()
                    if b != block:
                        block = b
                        place, waiting, column, names = {}, {}, {}, []
                    first = place.get(cid)
                    node = (node_id, np.full(most, never, np.int32) if first is None else first.copy(), own, cid, sid, uses)
                if dst is not None:
                    ahead = waiting[dst]  # missing: the order is not topological
                    np.minimum(node[1], ahead[1], out=node[1])
                    ahead[0] -= 1
                    if not ahead[0]:
                        del waiting[dst]
            if found:
                yield out()
        settle()
        yield out()

    return cut(laid.mapInArrow(sweep, "cid long, sid int, to_cid long, to_sid int"))


def three_leg_cover(entries: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Compression by middle chains: an entry (c -> t) is left out where it follows from entries c -> m and m -> t.

    Entries have a fixed order (of a hash), and one is left out only if both legs of
    a detour come before it.  The legs may be left out themselves; since the order
    has no cycles, following detours ends at entries that stay (see
    ``ThreeLegIndex``).  Returns (kept, left out).
    """
    before = F.lag("sid", 1, 0).over(Window.partitionBy("cid", "to_cid").orderBy("sid"))
    served = entries.withColumn("after", before)
    one = entries.select("cid", "sid", F.col("to_cid").alias("mid"), F.col("to_sid").alias("mid_sid"))
    # each place of an entry's interval as a row, and only detours to where the place has an entry: joins by equality
    two = served.select(F.col("cid").alias("mid"), F.explode(F.sequence(F.col("after") + 1, F.col("sid"))).alias("mid_sid"), F.col("sid").alias("leg_sid"), "to_cid", "to_sid")
    detour = one.join(entries, ["cid", "sid"]).filter("mid <> to_cid").join(two, ["mid", "mid_sid", "to_cid", "to_sid"])
    order = F.xxhash64("cid", "sid", "to_cid", "to_sid")
    leg1 = F.xxhash64("cid", "sid", "mid", "mid_sid")
    leg2 = F.xxhash64("mid", "leg_sid", "to_cid", "to_sid")
    gone = cut(detour.filter((order > leg1) & (order > leg2)).select("cid", "sid", "to_cid", "to_sid").distinct())
    return entries.join(gone, ["cid", "sid", "to_cid", "to_sid"], "left_anti"), gone


class ChainIndex(Reach):
    """Chains, entries and set tests by contours, on any digraph (cycles are condensed first)."""

    def __init__(self, chains: DataFrame, entries: DataFrame, scc: DataFrame | None = None):
        """``scc`` None: no node lies on a cycle, and the chains hold the places of all."""
        self.chains, self.entries, self.scc = chains, entries, scc
        if scc is None:
            self.scc = chains.select("node_id", F.col("node_id").alias("comp"), F.lit(False).alias("cyclic"))
            self.places = chains.select("node_id", "cid", "sid", F.lit(False).alias("cyclic"))
            return
        place = chains.withColumnRenamed("node_id", "comp")
        #: (node_id, cid, sid, cyclic) of every data node
        self.places = cut(scc.join(place, "comp").select("node_id", "cid", "sid", "cyclic"))

    @classmethod
    def build(cls, nodes: DataFrame, edges: DataFrame, chains: DataFrame | None = None, acyclic: bool = False, order: tuple[str, ...] = (), ends: DataFrame | None = None) -> ChainIndex:
        """``order``: columns of the nodes of an acyclic graph whose order is topological; entries then come from one pass.
        ``ends`` (with ``order``): the chains (cid) that all targets of the tests to come lie on; None: any."""
        if acyclic:
            scc = cut(nodes.select("node_id", F.col("node_id").alias("comp"), F.lit(False).alias("cyclic")))
            dag = cut(edges.select("src", "dst").distinct())
        else:
            scc, dag = condense(nodes, edges)
        if chains is None:
            chains = greedy_chains(scc.select(F.col("comp").alias("node_id")).distinct(), dag)
        chains = cut(chains)
        entries = swept_lists(chains, dag, nodes.select("node_id", *order), ends=ends) if acyclic and order else entry_lists(chains, dag)
        index = cls(chains, entries, scc)
        index.dag = dag
        return index

    @classmethod
    def swept(cls, rows: DataFrame, keys: list[str], ends: DataFrame) -> ChainIndex:
        """An acyclic graph's index off rows that are written already and hold all that the pass needs (see ``_swept``), each
        node once: nothing else is written, but for the entries."""
        return cls(rows.select("node_id", "cid", "sid"), _swept(rows.select("node_id", "cid", "sid", "uses", "dst", *keys), keys, ends))

    def save(self, folder: str) -> None:
        for name in ("chains", "entries", "scc"):
            getattr(self, name).write.mode("overwrite").parquet(f"{folder}/{name}")

    @classmethod
    def load(cls, spark, folder: str) -> ChainIndex:
        return cls(*(spark.read.parquet(f"{folder}/{name}") for name in ("chains", "entries", "scc")))

    # contours

    def _of(self, nodes: DataFrame) -> DataFrame:
        return self.places.join(small(nodes.select("node_id")), "node_id", "left_semi")

    def pred_contour(self, nodes: DataFrame) -> DataFrame:
        """(cid, pos_refl, pos_strict): the last place of each chain that reaches a member."""
        own = self._of(nodes).groupBy("cid").agg(F.max("sid").alias("r"), F.max(F.when(F.col("cyclic"), F.col("sid")).otherwise(F.col("sid") - 1)).alias("s"))
        own = cut(own)
        far = self.entries.join(small(own.select(F.col("cid").alias("to_cid"), "r")), "to_cid").filter("to_sid <= r").groupBy("cid").agg(F.max("sid").alias("r")).withColumn("s", F.col("r"))
        return own.union(far.select("cid", "r", "s")).groupBy("cid").agg(F.max("r").alias("pos_refl"), F.max("s").alias("pos_strict"))

    def succ_contour(self, nodes: DataFrame) -> DataFrame:
        """(cid, pos_refl, pos_strict): the first place of each chain that a member reaches."""
        own = self._of(nodes).groupBy("cid").agg(F.min("sid").alias("r"), F.min(F.when(F.col("cyclic"), F.col("sid")).otherwise(F.col("sid") + 1)).alias("s"))
        own = cut(own)
        far = self.entries.join(small(own.select("cid", F.col("r").alias("lo"))), "cid").filter("sid >= lo").groupBy("to_cid").agg(F.min("to_sid").alias("r")).select(F.col("to_cid").alias("cid"), "r", F.col("r").alias("s"))
        return own.union(far).groupBy("cid").agg(F.min("r").alias("pos_refl"), F.min("s").alias("pos_strict"))

    def _tested(self, rows: DataFrame, contour: DataFrame, test: str) -> DataFrame:
        """The rows whose place passes the test against the one row of its chain, with all their columns."""
        placed = small(rows).join(self.places.select("node_id", "cid", "sid"), "node_id")
        return placed.join(small(cut(contour)), "cid").filter(test).select(*rows.columns)

    def reaching(self, sources, targets):
        return self._tested(sources, self.pred_contour(targets), "sid <= pos_strict")

    def reachable(self, sources, targets):
        return self._tested(targets, self.succ_contour(sources), "sid >= pos_strict")

    def pairs(self, sources, targets):
        """Each source's first reachable places joined with the targets' places (a range join on the chain).  A source
        has one first place on a chain, so that every pair comes once."""
        return self.walked(sources.select(F.col("node_id").alias("src")).distinct(), "src", "dst", sources, targets)

    def walked(self, rows, at, name, sources, targets):
        """Rows are multiplied by runs of targets first, then each by the run's members, so that what a task holds at a time does
        not grow with the targets."""
        t = cut(self._of(targets).select("node_id", "cid", "sid").distinct().withColumn("@nth", F.row_number().over(Window.partitionBy("cid").orderBy("sid", "node_id")) - 1))
        members = F.sort_array(F.collect_list(F.struct("@nth", "node_id")))["node_id"]
        runs = cut(t.groupBy("cid", F.floor(F.col("@nth") / RUN).cast("int").alias("@run")).agg(members.alias("@members")))
        n, most = runs.agg(F.count("*"), F.coalesce(F.sum(F.size("@members")), F.lit(0))).first()
        # the number of targets before a source's first place, by one pass over both
        first = self._firsts(self._of(sources).distinct(), runs.select("cid"))
        both = t.select("cid", "sid", F.lit(1).alias("member"), F.lit(None).cast(first.schema["node_id"].dataType).alias("node_id")).union(first.select("cid", "first", F.lit(0), "node_id"))
        before = F.sum("member").over(Window.partitionBy("cid").orderBy("sid", "member").rowsBetween(Window.unboundedPreceding, Window.currentRow))
        before = cut(both.withColumn("@before", before).filter("member = 0").select(F.col("node_id").alias(at), "cid", F.col("@before").cast("int").alias("@before")))
        ahead = rows.join(small(before), at).join(small(runs.select("cid", "@run"), n), "cid").withColumn("@left_out", F.col("@before") - F.col("@run") * RUN).filter(F.col("@left_out") < RUN)
        held = apart(ahead.drop("@before")).join(small(runs, most), ["cid", "@run"])
        return held.select(*rows.columns, "@left_out", F.posexplode("@members").alias("@nth", name)).filter("`@nth` >= `@left_out`").select(*rows.columns, name)

    def _firsts(self, placed: DataFrame, ends: DataFrame, reflexive: bool = False) -> DataFrame:
        """(node_id, cid, first): the first place of each of the chains ``ends`` that each placed node reaches, one pass
        over the nodes and entries of each pair of chains; nodes' own chains are always among the rows."""
        s = cut(placed.select("node_id", "cid", "sid", "cyclic"))
        chains = small(cut(ends.select(F.col("cid").alias("to_cid")).distinct()))
        own = s.select("node_id", "cid", F.when(F.col("cyclic") | F.lit(reflexive), F.col("sid")).otherwise(F.col("sid") + 1).alias("first"))
        # the entry that serves a place is the next of its chain from the place on
        asked = s.crossJoin(chains).filter("cid <> to_cid").select("cid", "to_cid", "sid", F.lit(1).alias("asks"), "node_id", F.lit(None).cast("int").alias("to_sid"))
        given = self.entries.join(chains, "to_cid", "left_semi").join(small(cut(s.select("cid").distinct())), "cid", "left_semi").select("cid", "to_cid", "sid", F.lit(0).alias("asks"), F.lit(None).cast(s.schema["node_id"].dataType).alias("node_id"), "to_sid")
        serving = F.last("to_sid", ignorenulls=True).over(Window.partitionBy("cid", "to_cid").orderBy(F.desc("sid"), "asks").rowsBetween(Window.unboundedPreceding, Window.currentRow))
        far = asked.union(given).withColumn("first", serving).filter("asks = 1 and first is not null").select("node_id", F.col("to_cid").alias("cid"), "first")
        return own.union(far)

    #: whether every place that a node reaches is in the entries of its own chain
    complete = True

    @property
    def summed(self):
        return self._summed if self.complete else None

    def weighed(self, sources, targets):
        return self._summed(sources, targets) if self.complete else super().weighed(sources, targets)

    def _summed(self, sources: DataFrame, targets: DataFrame, reflexive: bool = False) -> DataFrame:
        """``weighed`` without making the pairs: a source's first place on each of the targets' chains, then running
        sums of the targets from the chain's end.  Rows are sources times the targets' chains."""
        t = cut(self.places.join(targets.select("node_id", F.col("n").cast("decimal(38,0)").alias("n")), "node_id").groupBy("cid", "sid").agg(F.sum("n").alias("n")))
        s = cut(self._of(sources).select("node_id", "cid", "sid", "cyclic"))
        places = self._firsts(s, t.select("cid"), reflexive).select("cid", F.col("first").alias("sid"), "node_id", F.lit(None).cast("decimal(38,0)").alias("n"))
        both = t.select("cid", "sid", F.lit(None).cast(s.schema["node_id"].dataType).alias("node_id"), "n").union(places)
        ahead = F.sum("n").over(Window.partitionBy("cid").orderBy(F.desc("sid")).rangeBetween(Window.unboundedPreceding, Window.currentRow))
        return both.withColumn("m", ahead).filter("node_id is not null and m is not null").groupBy("node_id").agg(F.sum("m").alias("m"))

    def closure_sizes(self) -> DataFrame:
        """(node_id, n): how many nodes each node of an acyclic graph reaches, without making the pairs."""
        long = self.chains.groupBy("cid").agg(F.max("sid").alias("top"))
        before = F.lag("sid", 1, 0).over(Window.partitionBy("cid", "to_cid").orderBy("sid"))
        served = self.entries.withColumn("after", before)
        each = served.join(F.broadcast(long.withColumnRenamed("cid", "to_cid")), "to_cid").select("cid", F.explode(F.sequence(F.col("after") + 1, F.col("sid"))).alias("sid"), (F.col("top") - F.col("to_sid") + 1).alias("far"))
        far = each.groupBy("cid", "sid").agg(F.sum("far").alias("far"))
        return self.places.join(long, "cid").join(far, ["cid", "sid"], "left").select("node_id", (F.col("top") - F.col("sid") + F.coalesce("far", F.lit(0))).cast("long").alias("n"))

    # lists of single nodes

    def successors(self, node_id: int) -> DataFrame:
        """Complete successor list of a node: chain -> first reachable place (its own place included)."""
        one = self.places.filter(F.col("node_id") == node_id)
        far = one.join(self.entries.withColumnRenamed("sid", "at"), "cid").filter("at >= sid").groupBy(F.col("to_cid").alias("cid")).agg(F.min("to_sid").alias("sid"))
        return one.select("cid", "sid").union(far.select("cid", "sid"))

    def predecessors(self, node_id: int) -> DataFrame:
        """Complete predecessor list: chain -> last place that reaches the node (its own place included)."""
        one = self.places.filter(F.col("node_id") == node_id).select(F.col("cid").alias("to_cid"), F.col("sid").alias("own"))
        far = one.join(self.entries, "to_cid").filter("to_sid <= own").groupBy("cid").agg(F.max("sid").alias("sid"))
        return one.select(F.col("to_cid").alias("cid"), F.col("own").alias("sid")).union(far.select("cid", "sid"))

    def reaches(self, pairs: DataFrame) -> DataFrame:
        """The pairs (src, dst) with ``reaches``: whether a nonempty path leads from the first to the second."""
        a = self.places.select(F.col("node_id").alias("src"), F.col("cid").alias("a_cid"), F.col("sid").alias("a_sid"), "cyclic")
        b = self.places.select(F.col("node_id").alias("dst"), F.col("cid").alias("to_cid"), F.col("sid").alias("b_sid"))
        asked = cut(pairs.select("src", "dst").distinct().join(a, "src").join(b, "dst"))
        own = asked.filter("a_cid = to_cid and (a_sid < b_sid or a_sid = b_sid and cyclic)").select("src", "dst")
        far = asked.filter("a_cid <> to_cid").join(self.entries.withColumnRenamed("cid", "a_cid"), ["a_cid", "to_cid"]).filter("sid >= a_sid and to_sid <= b_sid").select("src", "dst")
        hit = own.union(far).distinct().withColumn("hit", F.lit(True))
        return pairs.join(hit, ["src", "dst"], "left").withColumn("reaches", F.coalesce("hit", F.lit(False))).drop("hit")

    def trace_pointers(self) -> DataFrame:
        """(cid, sid, next_sid): for every place the next place of its chain, itself included, that has entries; null
        where there is none.  Look-ups here are range matches and need no pointers; the table shows what they skip."""
        full = self.entries.select("cid", "sid").distinct().withColumn("full", F.col("sid"))
        ahead = Window.partitionBy("cid").orderBy("sid").rowsBetween(Window.currentRow, Window.unboundedFollowing)
        return self.chains.select("cid", "sid").distinct().join(full, ["cid", "sid"], "left").select("cid", "sid", F.min("full").over(ahead).alias("next_sid"))

    def stats(self) -> dict[str, int]:
        """Nodes, chains and entries (|L_out| = |L_in| here: one table serves both directions)."""
        return {"nodes": self.places.count(), "chains": self.chains.select("cid").distinct().count(), "entries": self.entries.count()}


class ThreeLegIndex(ChainIndex):
    """The chain index on what ``three_leg_cover`` keeps: look-ups follow the kept entries through middle chains.

    Contours and lists go on from chain to chain until nothing improves; as a
    left-out entry's legs come before it in a fixed order, a few rounds do, each a
    join of the small contour with the kept entries.
    """

    complete = False

    @classmethod
    def of(cls, index: ChainIndex) -> ThreeLegIndex:
        return cls(index.chains, cut(three_leg_cover(index.entries)[0]), index.scc)

    def _led(self, start: DataFrame, forward: bool, most_rounds: int = 64) -> DataFrame:
        """(who, cid, sid): for each ``who`` the first (last, going backward) place of every chain that
        one or more kept entries lead to (from) from its start."""
        frm, at, to, place = ("cid", "sid", "to_cid", "to_sid") if forward else ("to_cid", "to_sid", "cid", "sid")
        best, within, further = (F.min, "at >= sid", "sid < had") if forward else (F.max, "at <= sid", "sid > had")
        steps = self.entries.select(F.col(frm).alias("cid"), F.col(at).alias("at"), F.col(to).alias("next"), F.col(place).alias("place"))
        known = front = cut(start.groupBy("who", "cid").agg(best("sid").alias("sid")))
        led = known.limit(0)
        for _ in range(most_rounds):
            far = cut(steps.join(front, "cid").filter(within).groupBy("who", F.col("next").alias("cid")).agg(best("place").alias("sid")))
            front = cut(far.join(known.withColumnRenamed("sid", "had"), ["who", "cid"], "left").filter(f"had is null or {further}").select("who", "cid", "sid"))
            led = cut(led.union(far).groupBy("who", "cid").agg(best("sid").alias("sid")))
            if front.isEmpty():
                return led
            known = cut(known.union(front).groupBy("who", "cid").agg(best("sid").alias("sid")))
        raise RuntimeError("the middle chains did not settle")

    def _contour(self, nodes: DataFrame, forward: bool) -> DataFrame:
        return self._contour_of(self._of(nodes), forward)

    def _contour_of(self, of: DataFrame, forward: bool) -> DataFrame:
        best, step = (F.min, 1) if forward else (F.max, -1)
        own = of.groupBy("cid").agg(best("sid").alias("r"), best(F.when(F.col("cyclic"), F.col("sid")).otherwise(F.col("sid") + step)).alias("s"))
        led = self._led(of.select(F.lit(0).alias("who"), "cid", "sid"), forward).select("cid", F.col("sid").alias("r"), F.col("sid").alias("s"))
        return own.union(led).groupBy("cid").agg(best("r").alias("pos_refl"), best("s").alias("pos_strict"))

    def pred_contour(self, nodes):
        return self._contour(nodes, False)

    def succ_contour(self, nodes):
        return self._contour(nodes, True)

    def pairs(self, sources, targets):
        return self._pairs_of(self._of(sources), self._of(targets))

    def walked(self, rows, at, name, sources, targets):
        return Reach.walked(self, rows, at, name, sources, targets)

    def _pairs_of(self, of: DataFrame, to: DataFrame) -> DataFrame:
        own = of.select(F.col("node_id").alias("who"), "cid", F.when(F.col("cyclic"), F.col("sid")).otherwise(F.col("sid") + 1).alias("first"))
        led = self._led(of.select(F.col("node_id").alias("who"), "cid", "sid"), True).select("who", "cid", "sid")
        t = to.select(F.col("node_id").alias("dst"), "cid", F.col("sid").alias("place"))
        return own.union(led).join(t, "cid").filter("place >= first").select(F.col("who").alias("src"), "dst").distinct()

    def _list(self, node_id: int, forward: bool) -> DataFrame:
        one = self.places.filter(F.col("node_id") == node_id).select(F.lit(0).alias("who"), "cid", "sid")
        return one.union(self._led(one, forward)).select("cid", "sid")

    def successors(self, node_id):
        return self._list(node_id, True)

    def predecessors(self, node_id):
        return self._list(node_id, False)

    def reaches(self, pairs):
        hit = self.pairs(pairs.select(F.col("src").alias("node_id")), pairs.select(F.col("dst").alias("node_id"))).withColumn("hit", F.lit(True))
        return pairs.join(hit, ["src", "dst"], "left").withColumn("reaches", F.coalesce("hit", F.lit(False))).drop("hit")

    def closure_sizes(self):
        raise NotImplementedError("closure sizes take complete entry lists")


class LinkIndex(ThreeLegIndex):
    """The chain index of an acyclic graph with the edges between chains as its only entries.

    Complete entry lists can grow to nodes times chains; here every longer entry
    is left out, since edges lead to it through middle chains, and the tables stay
    as large as the graph.  ``rank`` grows along every edge, so a test between two
    sets reads the entries from the least rank of the sources up to the greatest
    of the targets, and its rounds are the steps between these.
    """

    def __init__(self, places: DataFrame, entries: DataFrame, rounds: int | None = None):
        #: most entries of a path, where that is known
        self.rounds = rounds
        #: places(node_id, cid, sid, cyclic, rank), entries(cid, sid, to_cid, to_sid, rank, to_rank)
        self.places, self.entries = places, entries
        self.chains = places.select("node_id", "cid", "sid")
        self.scc = places.select("node_id", F.col("node_id").alias("comp"), "cyclic")

    @classmethod
    def build(cls, nodes: DataFrame, edges: DataFrame) -> LinkIndex:
        """``nodes``: (node_id, rank).  Edges whose ends are not both among the nodes are left out."""
        nodes = cut(nodes.groupBy("node_id").agg(F.min("rank").alias("rank")))
        chains = greedy_chains(nodes.select("node_id"), edges.filter("src is not null and dst is not null"))
        number = cut(chains.filter("sid = 1").select(F.col("cid").alias("head"), F.monotonically_increasing_id().alias("cid")))
        places = cut(chains.withColumnRenamed("cid", "head").join(number, "head").join(nodes, "node_id").select("node_id", "cid", "sid", F.lit(False).alias("cyclic"), "rank"))
        a = places.select(F.col("node_id").alias("src"), "cid", "sid", "rank")
        b = places.select(F.col("node_id").alias("dst"), F.col("cid").alias("to_cid"), F.col("sid").alias("to_sid"), F.col("rank").alias("to_rank"))
        return cls(places, cut(edges.join(a, "src").join(b, "dst").filter("cid <> to_cid").select("cid", "sid", "to_cid", "to_sid", "rank", "to_rank")))

    def _placed(self, rows: DataFrame) -> DataFrame:
        return cut(rows.join(self.places, "node_id"))

    def _span(self, sources: DataFrame, targets: DataFrame) -> LinkIndex:
        """The index with the entries alone that a path between the two sets can take."""
        low, high = (rows.agg(best("rank")).first()[0] for rows, best in ((sources, F.min), (targets, F.max)))
        if low is None or high is None:
            return LinkIndex(self.places, self.entries.limit(0), 0)
        return LinkIndex(self.places, self.entries.filter((F.col("rank") >= low) & (F.col("to_rank") <= high)), max(0, high - low))

    def _led(self, start, forward, most_rounds=64):
        """Each entry raises the rank, so that a span of few ranks needs as few joins and nothing written between them."""
        if self.rounds is None:
            return super()._led(start, forward, most_rounds)
        frm, at, to, place = ("cid", "sid", "to_cid", "to_sid") if forward else ("to_cid", "to_sid", "cid", "sid")
        best, within = (F.min, "at >= sid") if forward else (F.max, "at <= sid")
        steps = self.entries.select(F.col(frm).alias("cid"), F.col(at).alias("at"), F.col(to).alias("next"), F.col(place).alias("place"))
        front = start.groupBy("who", "cid").agg(best("sid").alias("sid"))
        led = front.limit(0)
        for _ in range(self.rounds):
            front = steps.join(front, "cid").filter(within).groupBy("who", F.col("next").alias("cid")).agg(best("place").alias("sid"))
            if self.rounds > 2:
                front = cut(front)
                if front.isEmpty():
                    break
            led = led.union(front)
        return led.groupBy("who", "cid").agg(best("sid").alias("sid"))

    def reaching(self, sources, targets):
        a, b = self._placed(sources), self._placed(targets.select("node_id"))
        contour = cut(self._span(a, b)._contour_of(b, False))
        return a.join(small(contour), "cid").filter("sid <= pos_strict").select(*sources.columns)

    def reachable(self, sources, targets):
        a, b = self._placed(sources.select("node_id")), self._placed(targets)
        contour = cut(self._span(a, b)._contour_of(a, True))
        return b.join(small(contour), "cid").filter("sid >= pos_strict").select(*targets.columns)

    def pairs(self, sources, targets):
        a, b = self._placed(sources.select("node_id").distinct()), self._placed(targets.select("node_id").distinct())
        return self._span(a, b)._pairs_of(a, b)


class KindLinkIndex(LinkIndex):
    """The links of a graph whose kinds lie on no cycle and whose rows hold their edges; tests are bound to kinds.

    The cover is made kind by kind: along one edge set into and one out of a kind,
    a node goes on to its least successor, which takes its least suitor.  Rows are
    written once with their places (and the columns ``keep``, which a pattern tests);
    entries are read off the rows, for a test those alone whose edge sets lie
    between its two kinds.  Candidates from ``placed_graph`` carry their places.
    """

    def __init__(self, graph: PropertyGraph, ranks: dict[str, int], keep: tuple[str, ...] = ()):
        if not all(e.holder and e.rows is not None for e in graph.edges):
            raise ValueError("edges that no rows hold")
        self.graph, self.ranks, self.keep, self.bound = graph, ranks, keep, {}
        #: the edge sets that the cover goes along, by their targets
        self.into: dict[str, EdgeSet] = {}
        for e in graph.edges:
            if e.target not in self.into and e.source not in {x.source for x in self.into.values()}:
                self.into[e.target] = e
        self._rows: dict[str, DataFrame] = {}
        for kind in graph.nodes:
            self.rows(kind)
        placed = [self.placed(k).select(F.col("node_id").cast("decimal(38,0)").alias("node_id"), "cid", "sid", F.lit(False).alias("cyclic"), F.lit(ranks[k]).alias("rank")) for k in graph.nodes]
        links = [self.links(e).select("*", F.lit(ranks[e.source]).alias("rank"), F.lit(ranks[e.target]).alias("to_rank")) for e in graph.edges]
        super().__init__(reduce(DataFrame.union, placed), reduce(DataFrame.union, links))

    def _wide(self, kind: str) -> bool:
        """Whether ids of a kind name whole rows, so that a node has one row."""
        return self.graph.nodes[kind].schema["node_id"].dataType.typeName() != "long"

    def rows(self, kind: str) -> DataFrame:
        """A kind's rows (node_id, ids that they hold, columns kept, cid, sid, own); a chain is named by its head's ``own``:
        its id, or a negative number where ids are wide."""
        if kind not in self._rows:
            table, e = self.graph.nodes[kind], self.into.get(kind)
            own = {x.column for x in self.graph.edges if kind == (x.source if x.holder == "source" else x.target)}
            columns = ["node_id", *sorted(own | set(self.keep) & set(table.columns))]
            number = -(F.lit((self.ranks[kind] << KEY_BITS) + 1).cast("long") + F.monotonically_increasing_id())
            if self._wide(kind) and e is not None and e.holder == "target":
                rows = self._followers(table.select(*columns), e).withColumn("own", number)
            else:
                rows = table.select(*columns).distinct()
                # numbers are written, so that they stay
                rows = stored(rows.withColumn("own", number)) if self._wide(kind) else rows.withColumn("own", F.col("node_id"))
                rows = rows.join(self._before(rows, e), "own", "left") if e is not None else rows.withColumns({"over": F.lit(None).cast("long"), "place": F.lit(None).cast("int")})
            self._rows[kind] = stored(rows.select(*columns, F.coalesce("over", "own").alias("cid"), (F.coalesce("place", F.lit(0)) + 1).alias("sid"), *["own"] * self._wide(kind)))
        return self._rows[kind]

    def _followers(self, rows: DataFrame, e: EdgeSet) -> DataFrame:
        """The rows, each once, with ``over`` and ``place`` where a row is the least of those below its source node: all by one
        shuffle, to where the source is; rows that hold no source are dealt out by their own ids."""
        alone = -F.shiftrightunsigned(F.xxhash64("node_id"), 1) - 1
        last = F.lag("node_id").over(Window.partitionBy("spot").orderBy("node_id"))
        rows = rows.withColumn("spot", F.coalesce(F.col(e.column), alone)).withColumn("last", last).filter("last is null or last <> node_id")
        self.rows(e.source)
        above = self.placed(e.source).select(F.col("node_id").alias("spot"), F.col("cid").alias("up"), F.col("sid").alias("at"))
        least = F.col("last").isNull()
        return rows.join(above, "spot", "left").withColumns({"over": F.when(least, F.col("up")), "place": F.when(least, F.col("at"))})

    def _before(self, rows: DataFrame, e: EdgeSet) -> DataFrame:
        """(own, over, place): the nodes of the set's target kind that follow another, and its place.  A chain has one node of
        a kind at most, so that within a kind it names its node."""
        above = self.rows(e.source)
        if e.holder == "target":
            take = rows.filter(F.col(e.column).isNotNull()).groupBy(F.col(e.column).alias("src")).agg(F.min("own").alias("own")).groupBy("own").agg(F.min("src").alias("src"))
            return take.join(self.placed(e.source).withColumnRenamed("node_id", "src"), "src").select("own", F.col("cid").alias("over"), F.col("sid").alias("place"))
        suitor = (F.min("cid").alias("over"), F.min_by("sid", "cid").alias("place"))
        wish = above.filter(F.col(e.column).isNotNull()).groupBy(F.col(e.column).alias("node_id")).agg(*suitor).join(rows.select("node_id", "own").distinct(), "node_id")
        return wish.groupBy("over").agg(F.min("own").alias("own"), F.min("place").alias("place")).select("own", "over", "place")

    def placed(self, kind: str) -> DataFrame:
        """(node_id, cid, sid), each node once."""
        rows = self._rows[kind].select("node_id", "cid", "sid")
        return rows if self._wide(kind) else rows.groupBy("node_id").agg(F.min("cid").alias("cid"), F.min("sid").alias("sid"))

    def placed_graph(self) -> PropertyGraph:
        """The graph on the rows that are written: candidates carry what tests ask for, so that none is joined with the places.
        Wide ids that no other row names are replaced by the numbers of this index."""
        nodes, edges = {}, []
        named = {e.target if e.holder == "source" else e.source for e in self.graph.edges}
        for kind, rows in self._rows.items():
            if self._wide(kind) and kind not in named:
                rows = rows.drop("node_id").withColumnRenamed("own", "node_id")
            nodes[kind] = rows.withColumnsRenamed({"cid": "@cid", "sid": "@sid"})
        for e in self.graph.edges:
            rows = nodes[e.source if e.holder == "source" else e.target]
            ends = ("node_id", e.column) if e.holder == "source" else (e.column, "node_id")
            edges.append(replace(e, rows=rows, df=rows.select(F.col(ends[0]).alias("src"), F.col(ends[1]).alias("dst"))))
        return PropertyGraph(nodes, edges, self.graph.keys)

    def links(self, e: EdgeSet) -> DataFrame:
        """(cid, sid, to_cid, to_sid) of the edges of a set that lead to another chain; those to or from no node are left out."""
        holder, other = (e.source, e.target) if e.holder == "source" else (e.target, e.source)
        names = {"source": ("cid", "sid"), "target": ("to_cid", "to_sid")}
        here, there = names[e.holder], names["target" if e.holder == "source" else "source"]
        rows = self._rows[holder].select(F.col(e.column).alias("other"), F.col("cid").alias(here[0]), F.col("sid").alias(here[1]))
        ends = self.placed(other).select(F.col("node_id").alias("other"), F.col("cid").alias(there[0]), F.col("sid").alias(there[1]))
        return rows.join(ends, "other").filter("cid <> to_cid").select("cid", "sid", "to_cid", "to_sid")

    def between(self, source: str, target: str) -> Reach:
        if (source, target) not in self.bound:
            paths = self.graph.kind_paths(source, target)
            self.bound[source, target] = BoundLinks(self, source, target, paths) if paths else KindPaths([])
        return self.bound[source, target]


class BoundLinks(LinkIndex):
    """Tests between two kinds by the links of the edge sets between them.

    A step along an edge set goes from the places at hand to the ids that their
    rows name, and on to the places of the rows that these ids lead to; a set with
    few members thus meets the rows at the other end once, without a shuffle.
    """

    def __init__(self, index: KindLinkIndex, source: str, target: str, paths: list[list[EdgeSet]]):
        self.index, self.source, self.target = index, source, target
        self.sets = list({e.name: e for path in paths for e in path}.values())
        self.rounds = max(map(len, paths))
        #: the sources tested last, and their contour
        self._last: tuple = (None, None)

    @property
    def entries(self) -> DataFrame:
        return reduce(DataFrame.union, [self.index.links(e) for e in self.sets])

    def columns(self, end: str) -> set[str]:
        kind = self.source if end == "source" else self.target
        return {"@cid", "@sid"} | {e.column for e in self.sets if e.holder == end and kind == (e.source if end == "source" else e.target)}

    def _members(self, some: DataFrame, end: str) -> DataFrame:
        """The members' rows with their places: as they carry them, or read by their ids."""
        if self.columns(end) <= set(some.columns):
            return some.withColumnsRenamed({"@cid": "cid", "@sid": "sid"})
        return self._found(some, end).join(some.select("node_id"), "node_id", "left_semi")

    def _found(self, some: DataFrame, end: str) -> DataFrame:
        rows = self.index.rows(self.source if end == "source" else self.target)
        if rows.schema["node_id"].dataType != some.schema["node_id"].dataType:
            raise ValueError("ids of the placed graph without their places")
        return rows

    def _led(self, members: DataFrame, forward: bool, who: tuple[str, ...] = ()) -> list[DataFrame]:
        """(who, cid, sid): the places that one, two, ... entries lead to from the members' (or from, going backward)."""
        best, within = (F.min, "at >= sid") if forward else (F.max, "at <= sid")
        start, front, found = self.source if forward else self.target, members.select(*who, "cid", "sid"), []
        for n in range(self.rounds):
            parts = []
            for e in self.sets:
                near, far = (e.source, e.target) if forward else (e.target, e.source)
                held = e.holder == ("source" if forward else "target")  # the near row names the far node
                if near == start:
                    if n:
                        continue
                    hit = members.select(*who, F.col(e.column if held else "node_id").alias("id"))
                else:
                    at = self.index.rows(near).select(F.col(e.column if held else "node_id").alias("id"), "cid", F.col("sid").alias("at"))
                    hit = at.join(front, "cid").filter(within).select(*who, "id")
                ends = self.index.rows(far).select(F.col("node_id" if held else e.column).alias("id"), "cid", "sid")
                parts.append(ends.join(hit if forward else small(hit), "id", "inner" if who else "left_semi").select(*who, "cid", "sid"))
            front = reduce(DataFrame.union, parts).groupBy(*who, "cid").agg(best("sid").alias("sid"))
            if self.rounds > 2:
                front = cut(front)
                if front.isEmpty():
                    break
            found.append(front)
        return found

    def _contour(self, members: DataFrame, forward: bool) -> DataFrame:
        """(@cid, pos_strict)"""
        best, step = (F.min, 1) if forward else (F.max, -1)
        own = members.select("cid", F.col("sid") + step)
        return reduce(DataFrame.union, [own, *self._led(members, forward)]).toDF("@cid", "pos_strict").groupBy("@cid").agg(best("pos_strict").alias("pos_strict"))

    def _passed(self, rows: DataFrame, end: str, contour: DataFrame, test: str) -> DataFrame:
        if {"@cid", "@sid"} <= set(rows.columns):
            return rows.join(contour, "@cid").filter(test).select(*rows.columns)
        placed = self._found(rows, end).select("node_id", F.col("cid").alias("@cid"), F.col("sid").alias("@sid"))
        return _among(rows, placed.join(contour, "@cid").filter(test))

    def reaching(self, sources, targets):
        return self._passed(sources, "source", self._contour(self._members(targets, "target"), False), "`@sid` <= pos_strict")

    def reachable(self, sources, targets):
        if self._last[0] is not sources:
            self._last = sources, small(cut(self._contour(self._members(sources, "source"), True)))
        return self._passed(targets, "target", self._last[1], "`@sid` >= pos_strict")

    def pairs(self, sources, targets):
        a = self._members(sources, "source").withColumn("src", F.col("node_id"))
        b = self._members(targets, "target").select(F.col("node_id").alias("dst"), "cid", "sid").distinct()
        own = a.select("src", "cid", (F.col("sid") + 1).alias("first"))
        first = reduce(DataFrame.union, [own, *self._led(a, True, ("src",))])
        return first.join(b, "cid").filter("sid >= first").select("src", "dst").distinct()
