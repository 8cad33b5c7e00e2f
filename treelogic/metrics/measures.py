"""Measures over evaluations.  Each returns plain numbers or a small DataFrame."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treelogic.analysis.minimize import operator_twig_size
from treelogic.evaluate.engine import EvalResult, Options, Pipeline
from treelogic.graph.model import PropertyGraph
from treelogic.index.chains import ChainIndex
from treelogic.plans import cut, join_count, small
from treelogic.query.pattern import TreePattern


def time_query(run: Callable[[], DataFrame], repetitions: int = 3, warm_up: int = 1) -> dict[str, float]:
    """Mean and median seconds of running a query to its rows, all columns of which are made."""
    def rows() -> None:
        run().write.format("noop").mode("overwrite").save()

    for _ in range(warm_up):
        rows()
    took = []
    for _ in range(repetitions):
        start = time.perf_counter()
        rows()
        took.append(time.perf_counter() - start)
    return {"mean": statistics.fmean(took), "median": statistics.median(took)}


def result_size(df: DataFrame) -> int:
    return df.count()


def candidate_counts(result: EvalResult) -> dict[str, dict[str, int]]:
    """Candidates of each pattern node before the rounds and after each of them."""
    return {stage: {name: df.count() for name, df in tables.items()} for stage, tables in result.candidates.items()}


def index_stats(index: ChainIndex, pattern: TreePattern | None = None) -> dict[str, int]:
    """Sizes of the index, and the most look-ups of its lists that a pattern can cause."""
    out = index.stats()
    if pattern is not None:
        out["lookups_at_most"] = (pattern.size() - 1) * out["entries"]
    return out


def contour_stats(index: ChainIndex, nodes: DataFrame) -> dict[str, float]:
    """Rows of a set's contour against the rows of its members' complete lists."""
    contour = index.pred_contour(nodes).count()
    members = index.places.join(nodes.select("node_id"), "node_id", "left_semi")
    # a list has a row for each chain whose first place reached on the member's chain comes no later than the member
    first = cut(index.entries.groupBy(F.col("to_cid").alias("cid"), F.col("cid").alias("from_cid")).agg(F.min("to_sid").alias("at")))
    lists = members.join(small(first), "cid").filter("at <= sid").count() + members.count()
    return {"contour_rows": contour, "list_rows": lists, "ratio": contour / lists if lists else 1.0}


def intermediate_cells(result: EvalResult) -> dict[str, int]:
    """Cells of the answers as tuples against nodes and edges of the match graph."""
    edges = {k: e.count() for k, e in result.match_graph.items()}
    nodes = sum(result.candidates["up"][n].count() for n in result.metrics["core"])
    return {"tuple_cells": result.df.count() * len(result.df.columns), "graph_cells": nodes + sum(edges.values()), "edges": sum(edges.values())}


def duplicate_ratio(graph: PropertyGraph, pattern: TreePattern) -> tuple[int, int]:
    """(rows with all backbone nodes as outputs, distinct rows of the pattern's outputs)."""
    whole = Pipeline(graph, pattern.with_outputs(pattern.backbone()), Options()).run().df
    return whole.count(), whole.select(*pattern.outputs()).distinct().count()


def prune_timing(graph: PropertyGraph, pattern: TreePattern, **options) -> dict[str, float]:
    """Seconds of the two pruning rounds and of the two-pass filter over the whole graph."""
    from treelogic.baselines.twigs import prefilter

    p = Pipeline(graph, pattern, Options(**options))
    start = time.perf_counter()
    up = p.prune_up(p.prune_down(p.candidates()), p.core())
    for df in up.values():
        df.count()
    rounds = time.perf_counter() - start
    start = time.perf_counter()
    for df in prefilter(graph, pattern).values():
        df.count()
    return {"rounds": rounds, "prefilter": time.perf_counter() - start}


def size_distribution(runs: DataFrame, by: str = "size", value: str = "results") -> DataFrame:
    """Quartiles of result sizes by query size."""
    return runs.groupBy(by).agg(*[F.expr(f"percentile_approx({value}, {q})").alias(f"p{round(100 * q)}") for q in (0.25, 0.5, 0.75)], F.count("*").alias("runs"))


def sweep(engines: dict[str, Callable[[PropertyGraph, TreePattern], DataFrame]], graphs: dict[str, PropertyGraph], patterns: Iterable[tuple[str, TreePattern]], repetitions: int = 1) -> list[dict]:
    """Time and result size of each engine, graph and pattern."""
    rows = []
    patterns = list(patterns)
    for scale, graph in graphs.items():
        for name, pattern in patterns:
            for engine, run in engines.items():
                took = time_query(lambda run=run, graph=graph, pattern=pattern: run(graph, pattern), repetitions, 0)
                rows.append({"engine": engine, "scale": scale, "pattern": name, "size": pattern.size(), "seconds": took["mean"], "results": run(graph, pattern).count()})
    return rows


def representation_sizes(pattern: TreePattern) -> dict[str, int]:
    return operator_twig_size(pattern)


def joins(df: DataFrame) -> int:
    return join_count(df)


def graph_stats(graph: PropertyGraph) -> DataFrame:
    """(kind, nodes) and (edge set, edges) counts in one table."""
    spark = graph.spark
    parts = [n.agg(F.count("*").alias("n")).select(F.lit("node").alias("what"), F.lit(k).alias("name"), "n") for k, n in graph.nodes.items()]
    parts += [e.df.agg(F.count("*").alias("n")).select(F.lit("edge").alias("what"), F.lit(e.name).alias("name"), "n") for e in graph.edges]
    out = spark.createDataFrame([], "what string, name string, n long")
    for part in parts:
        out = out.union(part)
    return out


def same_set(a: DataFrame, b: DataFrame) -> bool:
    """Exact methods agree as sets."""
    b = b.select(*a.columns)
    return a.distinct().exceptAll(b.distinct()).isEmpty() and b.distinct().exceptAll(a.distinct()).isEmpty()


def io_bytes(spark) -> dict[str, int]:
    """Bytes read from inputs and moved by shuffles in this session so far, from the status store."""
    store = spark.sparkContext._jsc.sc().statusStore()
    stages = store.stageList(None)
    read = moved = 0
    for i in range(stages.size()):
        s = stages.apply(i)
        read += s.inputBytes()
        moved += s.shuffleWriteBytes()
    return {"read": int(read), "shuffled": int(moved)}
