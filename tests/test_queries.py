"""Queries against DuckDB on the small tables; the larger ones run in the driver's check."""

import duckdb
import pytest

from treelogic.workloads import registry

FAST = ["cand_attr_ops", "cand_missing_attr_false", "ad_commerce_expand", "w1_auction", "w2_auction", "w3_auction", "trio_and", "trio_or", "trio_andnot", "nested_not_or", "all_order_no_line", "prune_up_counts", "core_singleton_parent", "multi_output", "pc_relax", "mixed_pc_ad", "optional_edge", "activity_edges", "pred_contour_slice", "succ_contour_slice", "reach_set_slice", "random_pattern_small_2", "trade_scc", "baseline_decompose", "baseline_dnf_difference", "stream_chain_counts", "baseline_naive", "core_shrink", "core_components", "satisfiability_report", "containment_matrix", "minimize_trace", "representation_sizes", "dom_pattern", "hierarchical_twig", "event_formula", "nested_groups", "true_combinations", "w2_tree_cover", "cluster_sizes", "cluster_semijoin", "dom_tree_codes", "bound_outputs"]


@pytest.fixture(scope="module")
def tables(sf_dir):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", FAST)
def test_query(spark, sf_dir, tables, name):
    found = registry.queries()[name](spark, sf_dir)
    columns = sorted(found.columns)
    want = tables.execute(registry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == columns
    place = [names.index(c) for c in columns]
    assert sorted(tuple(r) for r in found.select(*columns).collect()) == sorted(tuple(r[i] for i in place) for r in want.fetchall())


def test_expected_counts(spark, sf_dir):
    q = registry.queries()
    assert [q[f"w{i}_auction"](spark, sf_dir).count() for i in (1, 2, 3)] == [56, 3, 1]
    assert [q[f"trio_{k}"](spark, sf_dir).count() for k in ("and", "or", "andnot")] == [77, 401, 166]


def test_twigs_on_pages(spark, sf_dir):
    counts = {r[0]: r[1] for r in registry.queries()["hierarchical_twig"](spark, sf_dir).collect()}
    assert counts["nested"] == counts["paths"] > 0


def test_entry_point_without_operators(spark, monkeypatch):
    import importlib
    import sys

    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 166
    gone = {k: v for k, v in sys.modules.items() if k.startswith("treelogic.llm")}
    for k in gone:
        monkeypatch.delitem(sys.modules, k)
    monkeypatch.setitem(sys.modules, "treelogic.llm", None)
    again = importlib.reload(__spark_entry__)
    assert "trio_and" in again.queries() and not any(k.startswith("op1_") for k in again.queries())
    monkeypatch.undo()
    importlib.reload(__spark_entry__)
