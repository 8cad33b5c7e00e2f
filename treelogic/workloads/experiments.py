"""The study's experiments on the given tables: each returns rows that can be compared by ratio.

``python -m treelogic.workloads.experiments [name ...]`` runs them and prints JSON lines.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

from treelogic.baselines import joins as J
from treelogic.baselines import twigs as T
from treelogic.evaluate.engine import Options, Pipeline, count_matches, evaluate
from treelogic.graph import catalog
from treelogic.graph.model import PropertyGraph
from treelogic.index.chains import ChainIndex, natural_chains
from treelogic.metrics import measures
from treelogic.workloads.patterns import auction, auction_draws, random_patterns, trio

SCALES = ("sf0.001", "sf0.01", "sf0.1")
ENGINES = {
    "pattern": lambda g, p: evaluate(g, p).df,
    "pattern_with_upward_round": lambda g, p: evaluate(g, p, prune_up=True, checkpoints=True).df,
    "decompose": lambda g, p: J.decompose_evaluate(g, p)[0],
    "hash_join": lambda g, p: J.hash_structural(g, p)[0],
    "hash_join_graph": lambda g, p: J.hash_structural(g, p, represent="graph")[0],
    "local_semijoin": lambda g, p: J.local_semijoin(g, p)[0],
    "pool_twig": lambda g, p: T.pool_twig(g, p)[0],
    "pool_twig_unfiltered": lambda g, p: T.pool_twig(g, p, filtered=False)[0],
}


def data_size_sweep(spark: SparkSession, root: str, scales: Iterable[str] = SCALES, engines: Iterable[str] = ("pattern", "decompose", "hash_join"), shapes: Iterable[int] = (1, 2, 3), draws: int = 10) -> list[dict]:
    """Auction shapes over growing data, averaged over label draws."""
    graphs = {s: catalog.commerce(spark, f"{root}/{s}") for s in scales}
    patterns = [(f"w{shape}_{a}_{b}", auction(shape, a, b)) for shape in shapes for a, b in auction_draws(draws)]
    return measures.sweep({e: ENGINES[e] for e in engines}, graphs, patterns)


def query_size_sweep(spark: SparkSession, root: str, scale: str = "sf0.01", engines: Iterable[str] = ("pattern", "decompose", "hash_join"), draws: int = 1) -> list[dict]:
    """Shapes 1 to 3, each holding the one before."""
    return data_size_sweep(spark, root, (scale,), engines, draws=draws)


def boolean_patterns(spark: SparkSession, root: str, scale: str = "sf0.01") -> list[dict]:
    """The order trio by the pattern engine, by decomposition into terms and by operator twigs."""
    engines = {"pattern": ENGINES["pattern"], "terms": J.dnf_evaluate, "operator_twig": J.operator_twig}
    return measures.sweep(engines, {scale: catalog.papers(spark, f"{root}/{scale}")}, [(k, trio(k)) for k in ("and", "or", "andnot")])


def pruning(spark: SparkSession, root: str, scale: str = "sf0.01") -> list[dict]:
    """Seconds of the two pruning rounds and of the two-pass filter over the whole graph, by query size."""
    g = catalog.commerce(spark, f"{root}/{scale}")
    return [{"pattern": f"w{shape}", "size": auction(shape).size()} | measures.prune_timing(g, auction(shape), prune_up=True, checkpoints=True) for shape in (1, 2, 3)]


def event_graph(spark: SparkSession, folder: str, below: int | None = None) -> tuple[PropertyGraph, ChainIndex]:
    g = catalog.activity(spark, folder, below)
    g = PropertyGraph({"event": g.nodes["event"]}, [e for e in g.edges if e.source == "event"])
    return g, ChainIndex.build(g.nodes["event"], g.all_edges(), natural_chains(g.nodes["event"], "k", "ts", "event_id"), acyclic=True, order=("ts", "event_id"))


GROUPS = {"small": (2, 50), "large": (200, 1200)}


def random_queries(spark: SparkSession, root: str, scale: str = "sf0.01", below: int | None = None, sizes: Iterable[int] = (5, 7, 9, 11, 13), each: int = 15, tries: int = 600) -> list[dict]:
    """Random patterns by size and result group; counted before they are enumerated.  Tuple and graph
    intermediates of the hash joins, and the cells of both forms in the pattern engine."""
    g, index = event_graph(spark, f"{root}/{scale}", below)
    rows = []
    for size in sizes:
        left = dict.fromkeys(GROUPS, each)
        for p in random_patterns(g, size, tries, seed=42 + size):
            if not any(left.values()):
                break
            n = count_matches(g, p, index=index)
            group = next((k for k, (lo, hi) in GROUPS.items() if lo <= n <= hi and left[k]), None)
            if group is None:
                continue
            left[group] -= 1
            result = Pipeline(g, p, Options(index=index)).run()
            rows.append({"size": size, "group": group, "results": n, "pattern_s": measures.time_query(lambda p=p: evaluate(g, p, index=index).df, 1, 0)["mean"], "hash_tuples_s": measures.time_query(lambda p=p: J.hash_structural(g, p, index=index)[0], 1, 0)["mean"], "hash_graph_s": measures.time_query(lambda p=p: J.hash_structural(g, p, represent="graph", index=index)[0], 1, 0)["mean"]} | measures.intermediate_cells(result))
    return rows


def ablation(spark: SparkSession, root: str, scale: str = "sf0.01") -> list[dict]:
    """The rounds switched off one by one: same answers, different joins."""
    g = catalog.commerce(spark, f"{root}/{scale}")
    rows = []
    for name, options in {"default": {}, "both rounds": {"prune_up": True}, "no upward round": {"prune_up": False}, "whole backbone": {"shrink": False}, "minimized": {"minimize": True}, "relaxed children": {"pc_mode": "relax"}}.items():
        df = evaluate(g, auction(2), **options).df
        rows.append({"options": name, "results": df.count(), "joins": measures.joins(df)})
    return rows


EXPERIMENTS = {f.__name__: f for f in (data_size_sweep, query_size_sweep, boolean_patterns, pruning, random_queries, ablation)}


def as_table(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([json.loads(json.dumps(r)) for r in rows])


def main(names: list[str]) -> None:
    spark = SparkSession.builder.config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in names or EXPERIMENTS:
        for row in EXPERIMENTS[name](spark, "/root/testdata"):
            print(json.dumps({"experiment": name} | row), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
