"""Queries over the whole events table against reachability by brute force."""

import json

import duckdb
import pytest

from treelogic.index.chains import entry_lists, natural_chains, swept_lists
from treelogic.plans import plan_text
from treelogic.workloads import registry


class Brute:
    """Events in order, the strict closure as bit sets of positions."""

    def __init__(self, folder):
        rows = duckdb.sql(f"SELECT event_id, user_id, event_type, props, ts FROM '{folder}/events.parquet' ORDER BY ts, event_id").fetchall()
        self.ids = [r[0] for r in rows]
        self.kind = [r[2] for r in rows]
        self.k = [json.loads(r[3])["k"] for r in rows]
        self.sid, self.next = [0] * len(rows), [set() for _ in rows]
        last, seen = {}, {}
        for i, r in enumerate(rows):
            seen[self.k[i]] = self.sid[i] = seen.get(self.k[i], 0) + 1
            for key in (("user", r[1]), ("topic", self.k[i])):
                if key in last:
                    self.next[last[key]].add(i)
                last[key] = i
        self.far = [0] * len(rows)
        for i in reversed(range(len(rows))):
            for j in self.next[i]:
                self.far[i] |= self.far[j] | 1 << j

    def some(self, kind, test=lambda k: True):
        return [i for i in range(len(self.ids)) if self.kind[i] == kind and test(self.k[i])]

    def reaches(self, i, j):
        return bool(self.far[i] >> j & 1)


@pytest.fixture(scope="module")
def brute(sf_dir):
    return Brute(sf_dir)


def rows(spark, sf_dir, name):
    import __spark_entry__

    return {tuple(r) for r in __spark_entry__.queries()[name](spark, sf_dir).collect()}


def test_closure_sizes_and_reach_set(spark, sf_dir, brute):
    sizes = rows(spark, sf_dir, "event_closure_sizes")
    assert sizes == {(e, brute.far[i].bit_count()) for i, e in enumerate(brute.ids)} and max(sizes)[0] >= registry.SLICE
    members = sum(1 << j for j in brute.some("purchase", lambda k: k < 10))
    assert rows(spark, sf_dir, "event_reach_set") == {(brute.ids[i],) for i in brute.some("view") if brute.far[i] & members}


def test_contours(spark, sf_dir, brute):
    top = {k: brute.k.count(k) for k in set(brute.k)}
    own = brute.some("purchase", lambda k: k < 10)
    members, want = sum(1 << j for j in own), {}
    for i, k in enumerate(brute.k):
        r, s = want.get(k, (0, 0))
        far = bool(brute.far[i] & members)
        want[k] = (max(r, brute.sid[i] if far or i in own else 0), max(s, brute.sid[i] if far else 0))
    assert rows(spark, sf_dir, "event_pred_contour") == {(k, r, s) for k, (r, s) in want.items() if r}
    own, want, after = brute.some("signup", lambda k: k < 5), {}, 0
    for j in own:
        after |= brute.far[j]
    for i, k in enumerate(brute.k):
        far = after >> i & 1
        if far or i in own:
            r, s = want.get(k, (10**9, top[k] + 1))
            want[k] = (min(r, brute.sid[i]), min(s, brute.sid[i]) if far else s)
    found = rows(spark, sf_dir, "event_succ_contour")
    assert {(k, r, min(s, top[k] + 1)) for k, r, s in found} == {(k, r, s) for k, (r, s) in want.items()}


def test_patterns(spark, sf_dir, brute):
    b, ids = brute, brute.ids
    want = {(ids[n0], ids[n1], ids[n2], ids[n3]) for n0 in b.some("view", lambda k: k == 6) for n1 in b.some("purchase", lambda k: k == 12) if b.reaches(n0, n1)
            for n2 in b.next[n0] for n3 in b.some("error", lambda k: k == 10) if b.reaches(n2, n3)}
    assert rows(spark, sf_dir, "event_pattern_small_1") == want
    want = {(ids[n0], ids[n1], ids[n2], ids[n3]) for n0 in b.some("click", lambda k: k == 12) for n1 in b.some("view", lambda k: k == 12) if b.reaches(n0, n1)
            for n2 in b.next[n1] for n3 in b.next[n0]}
    assert rows(spark, sf_dir, "event_pattern_large_1") == want
    errors = b.some("error", lambda k: k < 20)
    n = sum(b.reaches(i, j) for i in errors for j in errors)
    assert rows(spark, sf_dir, "event_strict_vs_reflexive") == {("strict", n), ("reflexive", n + len(errors))}


def test_sweep_equals_doubling(spark, sf_dir):
    g = registry.event_slice(spark, sf_dir)
    ev = g.nodes["event"]
    chains = natural_chains(ev, "user_id", "ts", "event_id")
    one, two = swept_lists(chains, g.all_edges(), ev.select("node_id", "ts", "event_id"), width=4), entry_lists(chains, g.all_edges())
    assert {tuple(r) for r in one.collect()} == {tuple(r) for r in two.collect()}


def test_entries_to_some_chains(spark, sf_dir):
    """A sweep that is asked for some chains gives their entries and no others."""
    g = registry.event_slice(spark, sf_dir)
    ev = g.nodes["event"]
    chains, order = natural_chains(ev, "user_id", "ts", "event_id"), ev.select("node_id", "ts", "event_id")
    ends = chains.filter("cid % 3 = 1").select("cid")
    some, whole = swept_lists(chains, g.all_edges(), order, width=4, ends=ends), swept_lists(chains, g.all_edges(), order, width=4)
    assert {tuple(r) for r in some.collect()} == {tuple(r) for r in whole.collect() if r["to_cid"] % 3 == 1} != set()


@pytest.mark.parametrize("name", ["event_pattern_small_1", "event_pattern_small_2"])
def test_tuples_are_not_shuffled(spark, sf_dir, brute, name):
    """Answers grow with the cube of the events: they and the pairs of an edge are made row by row, each once."""
    import __spark_entry__

    found = __spark_entry__.queries()[name](spark, sf_dir)
    plan = plan_text(found)
    assert not [w for w in ("Aggregate", "SortMergeJoin", "hashpartitioning(n1", "hashpartitioning(n2", "hashpartitioning(n3") if w in plan]
    b, got = brute, [tuple(r) for r in found.collect()]
    assert len(got) == len(set(got))
    if name == "event_pattern_small_2":
        assert set(got) == {(b.ids[n0], b.ids[n1], b.ids[n2], b.ids[n3]) for n0 in b.some("signup", lambda k: k == 4) for n1 in b.next[n0]
                            for n2 in b.some("click", lambda k: k == 5) if b.reaches(n0, n2) for n3 in b.some("view", lambda k: k == 4) if b.reaches(n2, n3)}


def test_slices_are_for_tests_only():
    import __spark_entry__

    assert not set(registry.TESTS_ONLY) & (set(__spark_entry__.queries()) | set(__spark_entry__.oracle_sql()))
    assert all(f"event_id < {registry.SLICE}" not in s for s in __spark_entry__.oracle_sql().values())


def test_experiment_defaults(spark, sf_dir):
    import inspect

    from treelogic.workloads import experiments as X

    of = {n: p.default for n, p in inspect.signature(X.random_queries).parameters.items()}
    assert of["below"] is None and of["each"] == 15 and of["sizes"] == (5, 7, 9, 11, 13)
    assert inspect.signature(X.data_size_sweep).parameters["draws"].default == 10
    g, index = X.event_graph(spark, sf_dir)
    assert index.stats()["nodes"] == spark.read.parquet(f"{sf_dir}/events.parquet").count()


def test_few_rows_are_kept_before_the_answers(spark, sf_dir, brute, monkeypatch):
    """Events are written once with places and next events, the pass reads each once, and of an untested child of single edges
    only those events are tested that follow a candidate of its parent."""
    import __spark_entry__

    from treelogic.index import chains

    b, laid, tested = brute, [], []
    swept, reaching = chains._swept, chains.ChainIndex.reaching
    monkeypatch.setattr(chains, "_swept", lambda rows, *a: laid.append(rows) or swept(rows, *a))
    monkeypatch.setattr(chains.ChainIndex, "reaching", lambda self, a, t: tested.append(a.count()) or reaching(self, a, t))
    found = __spark_entry__.queries()["event_pattern_small_1"](spark, sf_dir)
    assert laid[0].count() == len(b.ids) and len(laid) == 1
    firsts = b.some("view", lambda k: k == 6)
    assert max(tested) <= max(len(firsts), len({j for i in firsts for j in b.next[i]})) < len(b.ids) // 4
    assert not [line for line in plan_text(found).splitlines() if "Window" in line]


def test_timelines_with_missing_keys(spark, tmp_path):
    """Events of no topic or of no user, and ties in time: places and next events as the SQL counterparts order them, and the
    pass over them finds the same entries as the one over all edges."""
    import random
    from datetime import datetime, timedelta

    r = random.Random(3)
    data = [(i, datetime(2024, 1, 1) + timedelta(seconds=i // 3), r.choice([1, 2, 3, 4, None]), r.choice(["view", "error"]), 1.0, r.choice(['{"k": 1}', '{"k": 2}', '{"k": 5}', "{}"])) for i in range(90)]
    spark.createDataFrame(data, "event_id long, ts timestamp, user_id long, event_type string, value double, props string").write.parquet(str(tmp_path / "events.parquet"))
    rows_ = registry.timelines(spark, str(tmp_path))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    want = con.execute(f"WITH {registry._WHOLE_EV} SELECT a, b FROM e").fetchall()
    low = (1 << 56) - 1
    got = {(x["node_id"] & low, y & low) for x in rows_.collect() for y in (x["dst"], x["next"]) if y is not None}
    assert got == set(want)
    edges = spark.createDataFrame([(x["node_id"], y) for x in rows_.collect() for y in {x["dst"], x["next"]} if y is not None], "src long, dst long")
    places = rows_.select("node_id", "cid", "sid")
    assert places.filter("cid is null").count() == 0
    one = {tuple(x) for x in swept_lists(places, edges, rows_.select("node_id", "ts")).collect()}
    index = registry.ChainIndex.swept(rows_, ["ts"], places)
    assert {tuple(x) for x in index.entries.collect()} == one != set()


def events_of(spark, folder, data):
    """An events table of (user, type, topic), in the order of time, two events a second."""
    from datetime import datetime, timedelta

    made = [(i, datetime(2024, 1, 1) + timedelta(seconds=i // 2), user, kind, 1.0, "{}" if k is None else json.dumps({"k": k})) for i, (user, kind, k) in enumerate(data)]
    spark.createDataFrame(made, "event_id long, ts timestamp, user_id long, event_type string, value double, props string").write.parquet(f"{folder}/events.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["event_pattern_small_1", "event_pattern_small_2"])
def test_runs_of_targets(spark, tmp_path, monkeypatch, name):
    """Targets are joined in runs: those that begin before a source's first place, ties in time, missing users and topics."""
    import random

    import __spark_entry__

    from treelogic.index import chains

    monkeypatch.setattr(chains, "RUN", 3)
    r = random.Random(11)
    folder = events_of(spark, tmp_path, [(r.choice([1, 2, 3, None]), r.choice(["view", "purchase", "error", "signup", "click"]), r.choice([4, 5, 6, 10, 12, None])) for _ in range(450)])
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet/*.parquet'")
    want = sorted(con.execute(__spark_entry__.oracle_sql()[name]).fetchall())
    got = sorted(tuple(x) for x in __spark_entry__.queries()[name](spark, folder).collect())
    assert got == want and len(want) > 500


@pytest.mark.parametrize("name, firsts, others", [("event_pattern_small_1", ("view", 6), [("purchase", 12), ("error", 10)]), ("event_pattern_small_2", ("signup", 4), [("click", 5), ("view", 4)])])
def test_tasks_hold_few_tuples(spark, tmp_path, monkeypatch, name, firsts, others):
    """A task that hands out a tuple has made few others, though a first node is in 40,000 or 20,100 of them."""
    import __spark_entry__

    from treelogic.index import chains

    monkeypatch.setattr(chains, "RUN", 16, raising=False)
    found = __spark_entry__.queries()[name](spark, events_of(spark, tmp_path, [(1, *firsts), (1, *firsts)] + [(1, *e) for _ in range(200) for e in others]))
    one = found.limit(1)
    assert len(one.collect()) == 1

    inner = {"AdaptiveSparkPlanExec": "executedPlan", "ResultQueryStageExec": "plan"}

    def made(plan):
        kind = plan.getClass().getSimpleName()
        kids = [getattr(plan, inner[kind])()] if kind in inner else [plan.children().apply(i) for i in range(plan.children().size())]
        rows_made = plan.metrics().get("numOutputRows")
        return ([rows_made.get().value()] if rows_made.isDefined() else []) + [n for kid in kids for n in made(kid)]

    tuples = made(one._jdf.queryExecution().executedPlan())
    assert 0 < max(tuples) <= 1_000
