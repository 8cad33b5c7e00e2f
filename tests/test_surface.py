from treelogic import sql as surface
from treelogic.graph import catalog
from treelogic.metrics import measures
from treelogic.query.dsl import parse
from treelogic.sources import edge_list, read_patterns, write_patterns
from treelogic.streaming import events as streams
from treelogic.evaluate.engine import Options, Pipeline
from treelogic.workloads.patterns import auction, auction_draws


def test_match_sql_and_functions(spark, sf_dir):
    g = catalog.commerce(spark, sf_dir)
    df = surface.sql(g, "MATCH o:orders*{//l:lineitem!} where not l RETURN o.o_orderkey", view="no_lines")
    assert df.columns == ["o_orderkey"] and spark.table("no_lines").count() == 27
    surface.register(spark)
    html = "<article><p>a<b>c</b></p><p>d</p></article>"
    assert spark.sql(f"SELECT tag FROM parse_dom('{html}')").count() == 4
    found = spark.sql(f"SELECT match FROM tree_match('{html}', 'p*[tag = ''p'']" + "{/b![tag = ''b'']}')").collect()
    assert [r[0] for r in found] == ['{"p": 2}']


def test_sources(spark, tmp_path):
    (tmp_path / "edges.txt").write_text("# comment\n1 2\n2\t3\nx y\n")
    assert {tuple(r) for r in edge_list(spark, str(tmp_path / "edges.txt")).collect()} == {(1, 2), (2, 3)}
    p = parse("b*[tag = 'b']{//c!} where not c")
    write_patterns(spark, [p, p], str(tmp_path / "patterns"))
    assert [q.to_json() for q in read_patterns(spark, str(tmp_path / "patterns"))] == [p.to_json()] * 2


def test_measures(spark, sf_dir):
    g = catalog.commerce(spark, sf_dir)
    result = Pipeline(g, auction(1), Options(prune_up=True, checkpoints=True)).run()
    counts = measures.candidate_counts(result)
    for name in auction(1).nodes:
        assert counts["up"][name] <= counts["down"][name] <= counts["cand"][name]
    assert measures.joins(result.df) > 0 and measures.same_set(result.df, result.df)
    assert len(set(auction_draws())) == 10


def test_streaming_pairs(spark, sf_dir):

    stream = streams.next_pairs(streams.read_events(spark, sf_dir, "events*.parquet"), late="3650 days")
    rows = streams.run_once(stream, "append").filter("not closed").select("src", "dst")
    g = catalog.activity(spark, sf_dir)
    edges = next(e for e in g.edges if e.name == "next_of_user").df
    mask = (1 << 56) - 1
    want = {(a & mask, b & mask) for a, b in edges.collect()}
    assert {tuple(r) for r in rows.collect()} == want


def test_experiments_and_explain(spark, sf_dir):
    from treelogic.evaluate.engine import explain
    from treelogic.workloads import experiments as X

    root = sf_dir.rsplit("/", 1)[0]
    rows = X.query_size_sweep(spark, root, "sf0.001", ("pattern", "hash_join"))
    by = {}
    for r in rows:
        by.setdefault(r["pattern"], set()).add(r["results"])
    assert len(by) == 3 and all(len(v) == 1 for v in by.values())
    assert len({r["results"] for r in X.ablation(spark, root, "sf0.001")}) == 1
    text = explain(catalog.commerce(spark, sf_dir), parse("o:orders*{//l:lineitem!} where not l"))
    assert "asked for false" in text and "KindPaths of 1 paths" in text
