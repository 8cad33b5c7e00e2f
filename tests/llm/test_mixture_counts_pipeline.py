import collections

import duckdb
import numpy as np
import public_tokenizers
import pytest

import corpus_pipeline
from tests.llm.conftest import cluttered
from tests.llm.test_duplicates import brute_classes, brute_repeats
from treelogic.llm import mixture, registry
from treelogic.llm.token_counts import RULES, attribute, line_borders, section_counts, token_spans


@pytest.mark.parametrize("name", ["op4_topk_search", "op5_source_mixture"])
def test_sql(spark, sf_dir, name):
    found = registry.queries()[name](spark, sf_dir)
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    want = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(found.columns)
    assert sorted(tuple(r) for r in found.select(*names).collect()) == sorted(want.fetchall())


def fill(budget, children):
    """Shares a budget among (weight, capacity) by rounds: those that are full drop out."""
    given, open_ = {}, dict(children)
    while open_:
        weight = sum(w for w, _ in open_.values())
        full = [k for k, (w, c) in open_.items() if c * weight <= w * budget]
        if not full:
            return given | {k: w * budget // weight for k, (w, c) in open_.items()}
        k = min(full, key=lambda k: (open_[k][1] / open_[k][0], k))
        given[k] = open_[k][1]
        budget -= open_.pop(k)[1]
    return given


def test_budgets_go_to_siblings_first(spark):
    leaves = [("a", "x", 100), ("a", "y", 1000), ("b", "x", 50), ("b", "z", 2000), ("c", "x", 10)]
    df = spark.createDataFrame(leaves, "top string, low string, leaf_tokens long")
    weights = {"top": {"a": 5, "b": 4, "c": 1}, "low": {"x": 3}}
    for total in (0, 500, 1500, 2500, 10_000):
        found = {(r["top"], r["low"]): r["leaf_budget"] for r in mixture.budgets(df, ("top", "low"), weights, total, 1).collect()}
        tops = fill(total, {t: (weights["top"][t], sum(n for u, _, n in leaves if u == t)) for t in "abc"})
        want = {}
        for t in "abc":
            want |= {(t, k): v for k, v in fill(tops[t], {low: (weights["low"].get(low, 1), n) for u, low, n in leaves if u == t}).items()}
        assert found == want


def test_mixture(documents, odd, spark):
    rows = mixture.with_domain(documents.select("doc_id", "text", "lang", "source").union(odd.selectExpr("doc_id", "text", "cast(null as string)", "cast(null as string)")))
    out = mixture.mix_documents(cluttered(rows), mixture.LEVELS, mixture.WEIGHTS, (1, 2), max_epochs=1, seed=3).collect()
    assert len(out) == rows.count()
    total = sum(r["n_tokens"] for r in out)
    assert sum(r["taken_tokens"] for r in out) <= total // 2
    assert sum(r["taken_tokens"] for r in out) >= total // 2 - 200
    assert all(r["taken_tokens"] <= r["n_tokens"] and (r["epochs"] > 0) == (r["taken_tokens"] > 0) for r in out)
    part = collections.Counter((r["domain"], r["lang"], r["source"]) for r in out if 0 < r["taken_tokens"] < r["n_tokens"])
    assert max(part.values(), default=0) <= 1
    assert mixture.mix_documents(rows.limit(0), mixture.LEVELS, mixture.WEIGHTS, (1, 2)).collect() == []


def brute_sections(ends, borders, rule):
    out = [0.0] * (len(borders) - 1)
    start = 0
    for end in ends:
        inside = [sum(borders[i] <= b < borders[i + 1] for b in range(start, end)) for i in range(len(out))]
        if rule == "start":
            out[next(i for i, n in enumerate(inside) if n)] += 1
        elif rule == "end":
            out[max(i for i, n in enumerate(inside) if n)] += 1
        elif rule == "most":
            out[inside.index(max(inside))] += 1
        else:
            for i, n in enumerate(inside):
                out[i] += n / (end - start)
        start = end
    return out


def test_token_counts(some):
    path = str(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    text = "One line.\n\n\nTwo lines é日\n\n \nthree"
    ids, ends = token_spans(text, path)
    data = np.frombuffer(text.encode(), np.uint8)
    assert ends[-1] == len(data)
    for rule in RULES:
        assert np.allclose(attribute(ends, line_borders(data), rule), brute_sections(ends.tolist(), line_borders(data).tolist(), rule))
    rows = section_counts(cluttered(some), path).collect()
    of = collections.defaultdict(list)
    for r in rows:
        of[r["doc_id"]].append(r)
    assert len(of[100002]) == 1 and of[100002][0]["n_tokens"] == 0
    texts = {r[0]: r[1] or "" for r in some.collect()}
    for doc_id, parts in of.items():
        if doc_id not in (None, 5, 100001, 100003):
            assert sum(p["n_tokens"] for p in parts) == parts[0]["doc_tokens"]
            assert "".join(texts[doc_id][p["start_char"]:p["end_char"]] for p in sorted(parts, key=lambda p: p["section"])) == texts[doc_id]
    split = section_counts(some, path, rule="split").groupBy().sum("n_tokens").first()[0]
    assert abs(split - sum(r["n_tokens"] for r in rows)) < 1e-6


def test_own_sections(spark):
    path = str(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    df = spark.createDataFrame([(1, "héllo wörld and more", [6, 12]), (2, "abc", None), (3, "abc", [0, 2, 2, 9])], "doc_id long, text string, cuts array<int>")
    rows = {(r["doc_id"], r["section"]): (r["start_char"], r["end_char"]) for r in section_counts(df, path, sections="cuts").collect()}
    assert rows == {(1, 0): (0, 6), (1, 1): (6, 12), (1, 2): (12, 20), (2, 0): (0, 3), (3, 0): (0, 2), (3, 1): (2, 3)}


def test_stages(spark, documents, odd, sf_dir):
    docs = cluttered(documents.unionByName(odd.filter("doc_id is null or doc_id <> 5").selectExpr("doc_id", "text", "'en' lang", "'src1' source", "cast(1 as long) n_chars")))
    foreign = {200001, 200002}
    more = [(200001, "все люди рождаются свободными и равными в своем достоинстве и правах " * 3), (200002, "for (int i=0;i<n;i++){ x[i] += y[j] * 3.14; } while(z--){ q&=~w; }" * 4)]
    docs = docs.unionByName(spark.createDataFrame(more, "doc_id long, text string"), allowMissingColumns=True)
    columns = docs.columns
    names = dict(corpus_pipeline.STAGES)
    told = names["language_id"](spark, docs, sf_dir)
    assert told.columns == columns
    gone = {r["doc_id"] for r in docs.collect()} - {r["doc_id"] for r in told.collect()}
    # without a letter; made of few letters or of a script that was not learned; in no learned language
    assert gone == {100002, 100004, 100008} | {100001, None, 100006, 100007} | foreign
    docs = docs.filter("doc_id is null or doc_id < 200000")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    kept = names["near_duplicates"](spark, docs, sf_dir)
    assert kept.columns == columns
    classes = brute_classes(rows, 5, 4, 5)
    assert kept.count() == len({c for _, n, c in classes if n}) + sum(1 for d, t in set(rows) if not (t or "").split())
    cut = names["repeated_passages"](spark, docs, sf_dir)
    assert cut.columns == columns
    want = collections.Counter({k: v for k, v in brute_repeats(rows).items() if not (k[1] and k[1] == k[2])})
    assert cut.count() == sum(want.values())
    mixed = names["mix_sources"](spark, docs, sf_dir)
    assert mixed.columns == columns and 0 < mixed.count() < docs.count()
    for stage in names.values():
        assert stage(spark, docs.limit(0), sf_dir).collect() == []


def test_run(spark, sf_dir):
    assert 0 < corpus_pipeline.run(spark, sf_dir).count() < spark.read.parquet(f"{sf_dir}/documents.parquet").count()
