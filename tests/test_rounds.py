"""Both rounds run on graphs of foreign keys unless they are left to the joins."""

from treelogic.evaluate.engine import Options, Pipeline
from treelogic.graph import catalog
from treelogic.workloads.patterns import auction


def test_rounds_on_key_graphs(spark, sf_dir):
    g = catalog.commerce(spark, sf_dir)
    result = Pipeline(g, auction(2)).run()
    sizes = {stage: result.candidates[stage]["o"].distinct().count() for stage in ("cand", "down", "up")}
    assert sizes["up"] < sizes["down"] < sizes["cand"]
    plain = Pipeline(g, auction(2), Options(key_joins=True))
    assert plain.direct and not plain.upward
    assert {tuple(r) for r in plain.run().df.collect()} == {tuple(r) for r in result.df.collect()}
