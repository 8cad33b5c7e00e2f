"""Reports on what a given table asks for, against its rows; and counts by the chain index against its pairs."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

from treelogic.evaluate.engine import count_matches, evaluate
from treelogic.graph.model import from_rows
from treelogic.index.chains import ChainIndex, KindLinkIndex, LinkIndex
from treelogic.index.covers import KindCover, TreeCover
from treelogic.index.reach import KindPaths, Reach, Reflexive
from treelogic.metrics import measures
from treelogic.query.dsl import parse
from treelogic.query.reference import random_graph
from treelogic.workloads import registry


@pytest.mark.parametrize("name", ["bound_outputs", "containment_matrix", "minimize_trace", "representation_sizes", "satisfiability_report"])
def test_reports_read_the_orders(spark, tmp_path, name):
    """Keys of any sign, repeated and missing ones: each order counts where its keys point."""
    schema = "o_orderkey long, o_custkey long"
    spark.createDataFrame([(0, 0), (0, 0), (1, 1), (-1, 3), (None, 2), (7, None)], schema).write.parquet(str(tmp_path / "orders.parquet"))
    found = registry.queries()[name](spark, str(tmp_path))
    assert found.inputFiles()
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{tmp_path}/orders.parquet/*.parquet'")
    want = con.execute(registry.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert sorted(map(str, (tuple(r) for r in found.select(*columns).collect()))) == sorted(map(str, want.fetchall()))
    assert max(r["orders"] for r in found.collect()) == 2


@pytest.mark.parametrize("seed,density", [(1, 0.1), (4, 0.25)])
def test_counts_without_pairs(spark, seed, density):
    """Weighted counts equal those over the pairs, in both modes, cycles and sources without targets included."""
    g = random_graph(12, density, "ab", random.Random(seed))
    gg = from_rows(spark, [(i, a["tag"], a["val"]) for i, (_, a) in g.nodes.items()], list(g.edges))
    nodes = gg.nodes["node"].select("node_id")
    index = ChainIndex.build(nodes, gg.all_edges())
    some = gg.nodes["node"].filter("tag = 'b'").select("node_id", (F.col("node_id") + 1).cast("decimal(38,0)").alias("n"))
    for one in (index, Reflexive(index)):
        found = {tuple(map(int, r)) for r in one.weighed(nodes, some).collect()}
        assert found == {tuple(map(int, r)) for r in Reach.weighed(one, nodes, some).collect()} and found
    p = parse("x*[tag = 'a']{//y*[tag = 'b']{//z*[tag = 'a']}}")
    index.pairs = None  # not to be asked
    assert count_matches(gg, p, index=index) == evaluate(gg, p).df.count()


def test_list_rows_are_those_of_the_lists(spark):
    g = random_graph(12, 0.2, "ab", random.Random(2))
    gg = from_rows(spark, [(i, a["tag"], a["val"]) for i, (_, a) in g.nodes.items()], list(g.edges))
    index = ChainIndex.build(gg.nodes["node"].select("node_id"), gg.all_edges())
    some = gg.nodes["node"].filter("tag = 'a'")
    ids = [r[0] for r in some.select("node_id").collect()]
    assert measures.contour_stats(index, some)["list_rows"] == sum(index.predecessors(i).count() for i in ids)


def test_links_alone_answer_as_the_whole_index(spark):
    """A layered graph with repeated edges and edges to no node: pairs and set tests against walks."""
    r = random.Random(7)
    rank = {i: i // 5 for i in range(25)}
    edges = [(a, b) for a in rank for b in rank if rank[a] < rank[b] and r.random() < 0.12]
    far = {a: set() for a in rank}
    for a in sorted(rank, reverse=True):
        for x, b in edges:
            if x == a:
                far[a] |= {b} | far[b]
    nodes = spark.createDataFrame(list(rank.items()), "node_id long, rank int")
    index = LinkIndex.build(nodes.union(nodes.limit(3)), spark.createDataFrame([*edges, edges[0], (0, 99), (98, 3), (97, 24)], "src long, dst long"))
    ids = nodes.select("node_id")
    assert {tuple(x) for x in index.pairs(ids, ids).collect()} == {(a, b) for a in far for b in far[a]}
    for low, high in ((1, 3), (0, 4), (2, 2)):
        some, other = nodes.filter(f"rank = {low}").select("node_id"), nodes.filter(f"rank = {high} and node_id % 2 = 0").select("node_id")
        a, b = {x[0] for x in some.collect()}, {x[0] for x in other.collect()}
        assert {x[0] for x in index.reaching(some, other).collect()} == {x for x in a if far[x] & b}
        assert {x[0] for x in index.reachable(some, other).collect()} == {y for y in b if any(y in far[x] for x in a)}
    assert index.entries.count() <= len(edges) + 4  # no longer ones are stored


@pytest.mark.parametrize("name", ["w1_contour", "w2_contour", "w3_contour"])
def test_contours_on_links_equal_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    assert isinstance(registry.commerce_index(registry.catalog.commerce(spark, sf_dir)), LinkIndex)
    want = con.execute(registry.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert sorted(map(tuple, registry.queries()[name](spark, sf_dir).select(*columns).collect())) == sorted(want.fetchall())


def test_clusters_are_made_when_read(spark, sf_dir):
    """One table for each pair of kinds with a path, from the node tables themselves: no closure is written."""
    clusters = registry.commerce_clusters(registry.catalog.commerce(spark, sf_dir)).clusters
    assert len(clusters) == 20 and all(c.inputFiles() for c in clusters.values())


def test_cover_by_kinds(spark, sf_dir):
    """Codes of the forest, and the same pairs as the spanning tree's cover that is written, for one, for several steps and
    for steps that go on beside the forest; tests without kinds ask all of them."""
    g = registry.catalog.commerce(spark, sf_dir)
    cover, written = KindCover(g), TreeCover.build(g.all_nodes(), g.all_edges(), acyclic=True)
    code = cover.codes("lineitem").first()["code"]
    assert [int(i) >> 119 if i >= 1 << 63 else int(i) >> 56 for i in code] == [registry.catalog.CODES[k] for k in ("region", "nation", "customer", "orders", "lineitem")]
    some = {"nation": "n_nationkey % 3 = 0", "region": "r_regionkey < 2", "customer": "grp = 3", "supplier": "grp = 3", "part": "grp = 7", "lineitem": "grp = 1", "orders": "grp = 2"}
    sets = {k: g.nodes[k].filter(test).select("node_id") for k, test in some.items()}
    for a, b in (("customer", "lineitem"), ("region", "supplier"), ("nation", "part"), ("orders", "supplier"), ("lineitem", "part")):
        want = {tuple(map(int, r)) for r in written.pairs(sets[a], sets[b]).collect()}
        assert {tuple(map(int, r)) for r in cover.between(a, b).pairs(sets[a], sets[b]).collect()} == want != set()
        assert {int(r[0]) for r in cover.between(a, b).reaching(sets[a], sets[b]).collect()} == {x for x, _ in want}
    assert {int(r[0]) for r in cover.reachable(sets["region"], sets["supplier"]).collect()} == {int(r[0]) for r in written.reachable(sets["region"], sets["supplier"]).collect()}


@pytest.fixture(scope="module")
def odd_tables(sf_dir, tmp_path_factory):
    """The small tables with rows that come twice, keys that come twice with other foreign keys, and keys of no row or none."""
    folder, con = tmp_path_factory.mktemp("odd"), duckdb.connect()
    more = {
        "customer": "SELECT * REPLACE ((c_nationkey + 1) % 25 AS c_nationkey) FROM t WHERE c_custkey % 5 = 3",
        "orders": "SELECT * REPLACE (o_custkey + 10 AS o_custkey) FROM t WHERE o_orderkey % 3 = 0 UNION ALL SELECT * FROM t WHERE o_orderkey % 7 = 0",
        "lineitem": "SELECT * FROM t WHERE l_orderkey % 4 = 1 UNION ALL SELECT * REPLACE (NULL AS l_partkey, 900003 AS l_suppkey) FROM t WHERE l_orderkey % 9 = 2 UNION ALL SELECT * REPLACE (NULL AS l_orderkey) FROM t WHERE l_orderkey % 9 = 3",
    }
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        con.execute(f"CREATE TABLE {t} AS WITH t AS (FROM '{sf_dir}/{t}.parquet') SELECT * FROM t" + (f" UNION ALL {more[t]}" if t in more else ""))
        con.execute(f"COPY {t} TO '{folder}/{t}.parquet' (FORMAT parquet)")
    return str(folder), con


@pytest.mark.parametrize("name", ["w2_contour", "w3_contour"])
def test_odd_rows_by_kinds(spark, odd_tables, name):
    folder, con = odd_tables
    want = con.execute(registry.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    assert sorted(map(tuple, registry.queries()[name](spark, folder).select(*columns).collect())) == sorted(want.fetchall()) != []


def test_links_by_kinds(spark, odd_tables):
    """A node has one place and a place one node; pairs and set tests between kinds, of one step and of several, are those
    of the paths of kinds; an entry is read for those tests alone between whose kinds it lies."""
    g = registry.catalog.commerce(spark, odd_tables[0])
    index = registry.commerce_index(g)
    assert isinstance(index, KindLinkIndex)
    places = index.places.filter("node_id is not null")
    assert places.count() == places.select("node_id").distinct().count() == places.select("cid", "sid").distinct().count()
    sets = {k: rows.filter("grp < 4" if k not in ("region", "nation") else "node_id % 2 = 1").select("node_id") for k, rows in g.nodes.items()}
    for a, b in (("orders", "lineitem"), ("lineitem", "supplier"), ("customer", "part"), ("nation", "supplier")):
        one = index.between(a, b)
        want = {tuple(map(int, r)) for r in KindPaths(g.kind_paths(a, b)).pairs(sets[a], sets[b]).distinct().collect()}
        assert {tuple(map(int, r)) for r in one.pairs(sets[a], sets[b]).collect()} == want != set()
        assert {int(r[0]) for r in one.reaching(sets[a], sets[b]).collect()} == {x for x, _ in want}
        assert {int(r[0]) for r in one.reachable(sets[a], sets[b]).collect()} == {y for _, y in want}
    assert index.between("lineitem", "part").entries.count() < index.entries.count()
    assert not index.between("part", "region").pairs(sets["part"], sets["region"]).collect()


def test_candidates_carry_their_places(spark, odd_tables, monkeypatch):
    """Rows are written once with their places, which candidates carry: tests join them with contours alone, and no whole row
    is hashed again; answers, lines among them, are those of the paths of kinds."""
    from treelogic.evaluate.engine import Pipeline, candidates
    from treelogic.index import chains
    from treelogic.plans import plan_text

    g, written, stored = registry.catalog.commerce(spark, odd_tables[0]), [], chains.stored
    monkeypatch.setattr(chains, "stored", lambda df: written.append(df) or stored(df))
    index = registry.commerce_index(g)
    assert len(written) == len(g.nodes)
    placed = index.placed_graph()
    p = parse("o:orders*[grp = 3]{//l:lineitem*{//x:part*[grp = 7]}, //m:lineitem!{//s:supplier![grp = 3]}}")
    found = Pipeline(placed, p, registry.Options(index=index, force_index=True))
    cand = {u.name: candidates(placed, u, found.columns(u)) for u in p.root.walk()}
    plan = plan_text(found.operators["x"].reaching(cand["l"], cand["x"]))
    assert "xxhash64" not in plan and not any("Join [node_id#" in line for line in plan.splitlines())
    keys = [r for r in evaluate(placed, p, index=index, force_index=True).df.select("o", "x").collect()]
    assert sorted(map(tuple, keys)) == sorted(map(tuple, evaluate(g, p).df.select("o", "x").collect())) != []
    a, b = (placed.nodes[k].filter("grp < 4") for k in ("customer", "part"))  # in several steps
    want = {tuple(r) for r in KindPaths(g.kind_paths("customer", "part")).pairs(*(g.nodes[k].filter("grp < 4").select("node_id") for k in ("customer", "part"))).collect()}
    one = index.between("customer", "part")
    assert {tuple(r) for r in one.pairs(a, b).collect()} == want != set()
    assert {r[0] for r in one.reaching(a, b).select("node_id").collect()} == {x for x, _ in want}
    assert {r[0] for r in one.reachable(a, b).select("node_id").collect()} == {y for _, y in want}
    with pytest.raises(ValueError):
        index.between("orders", "lineitem").reachable(a.select("node_id"), placed.nodes["lineitem"].select("node_id"))
