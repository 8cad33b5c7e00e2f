import math
import re
import time
import zlib
from collections import Counter, defaultdict
from html import unescape

import numpy as np
import pyarrow as pa
import pytest

from tests.llm.conftest import cluttered
from treelogic.llm import html_tree, lang_ppm
from treelogic.llm.topk_search import MaxScore, top_k


def brute_bits(model, texts, data):
    """Code length of a text by the definition, one byte at a time; 256 stands before the first one."""
    total = []
    for name in model.languages:
        seen = [defaultdict(Counter) for _ in range(4)]
        for b in texts[name]:
            s = [256, 256, 256, *b]
            for i in range(3, len(s)):
                for d in range(4):
                    seen[d][tuple(s[i - d:i])][s[i]] += 1

        def prob(context, x):
            shorter = 1 / 256 if not context else prob(context[1:], x)
            counts = seen[len(context)].get(context)
            if not counts:
                return shorter
            return (max(counts[x] - 0.5, 0) + 0.5 * len(counts) * shorter) / sum(counts.values())

        s = [256, 256, 256, *data]
        total.append(sum(-math.log2(prob(tuple(s[i - 3:i]), s[i])) for i in range(3, len(s))))
    return total


def test_code_lengths(documents):
    texts = {}
    for r in documents.limit(120).collect():
        texts.setdefault(r["lang"], []).append(r["text"].encode())
    texts = {k: v[:6] for k, v in texts.items()}
    model = lang_ppm.fit(texts)
    column = pa.array(["", "a", "Das ist ein Test", None, "ééé the", "q!"] * 2)
    found, size = model.totals(column)
    for i, t in enumerate(column.to_pylist()):
        assert np.allclose(found[i], brute_bits(model, texts, (t or "").encode()), atol=1e-3)
    assert size.tolist() == [len((t or "").encode()) for t in column.to_pylist()]


def test_identification(documents, odd, spark):
    rows = documents.select("doc_id", "text", "lang").union(odd.selectExpr("doc_id", "text", "cast(null as string) lang"))
    out = lang_ppm.predict_held_out(cluttered(rows).drop("lang_pred").withColumnRenamed("part", "source")).collect()
    assert len(out) == rows.count()
    truth = {r["doc_id"]: r["lang"] for r in documents.collect()}
    held = [r for r in out if r["held_out"] and r["doc_id"] in truth and r["doc_id"] != 5]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in out if r["doc_id"] is not None)
    assert sum(r["lang_pred"] == truth[r["doc_id"]] for r in held) >= 0.95 * len(held)
    told = {r["doc_id"]: r["lang_pred"] for r in out}
    assert told[100002] == "und" and told[100004] == "und" and told[100008] == "und"
    assert all(0 <= r["score"] <= 1 for r in out)
    empty = lang_ppm.predict_held_out(rows.limit(0))
    assert empty.collect() == []


def test_marginals_equal_enumeration():
    """Sum-product on a small page against all labelings."""
    import itertools

    page = html_tree.parse("<body><nav><a>x</a></nav><article><p>Some text here.</p><p>More.</p></article></body>")
    model = html_tree.trained()
    forest = html_tree.Forest([page])
    found, _ = forest.marginals(model.weights, model.edge)
    n = len(page.parent)
    own = np.bincount(forest.owner, weights=model.weights[forest.flat], minlength=n)
    mass = np.zeros(n)
    total = 0.0
    for x in itertools.product((0, 1), repeat=n):
        w = math.exp(sum(own[v] for v in range(n) if x[v]) + sum(model.edge[x[page.parent[v]], x[v]] for v in range(1, n)))
        total += w
        mass += w * np.array(x)
    assert np.allclose(found, mass / total, atol=1e-9)


def test_held_out_pages():
    model = html_tree.trained()
    pages = html_tree.labelled_pages(150, seed=99)
    good = every = kept = 0
    for (html, content), text in zip(pages, model.texts([h for h, _ in pages])):
        blocks = [b for _, b in html_tree.parse(html).blocks]
        found = set(text.split("\n")) if text else set()
        want = {b for b in blocks if b in content}
        good += len(found & want)
        every += len(want)
        kept += len(found)
    assert good > 0.97 * every and good > 0.97 * kept


@pytest.mark.parametrize("html, want", [
    (None, ""), ("", ""), ("   ", ""), ("<!-- x -->", ""),
    ("<body><nav><a href='/'>Home</a></nav><article><h1>A &amp; B</h1><p>One  two\n three<br>four.</p><p>x &lt; y.</p></article><footer>foot</footer>", "A & B\nOne two three four.\nx < y."),
    ("<article><h1>Title here</h1><p><b>First.<br><p>Second one.</p></article><div class='comments'><h2>Comments</h2><p>Nice post, thanks a lot for it.</p></div>", "Title here\nFirst.\nSecond one."),
    ("<article><p>Text.</p><script>var t='</p>';</script><style>p{}</style><p>End.</p></article>", "Text.\nEnd."),
])
def test_pages(html, want):
    assert html_tree.trained().texts([html]) == [want]


def test_broken_markup_never_fails():
    for html in ("<", "<p", "<p class=\"x>text", "</p></div>", "<a href='", "<article><p>unclosed", "<script>never closed", "<table><tr><td>1<td>2<tr><td>3", "a < b > c", "<p>" * 3000):
        html_tree.parse(html)
        html_tree.trained().texts([html])


def test_pages_table(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    out = html_tree.extract(cluttered(pages)).collect()
    assert len(out) == pages.count() and all(r["n_chars"] == len(r["text"]) for r in out)
    # these pages' articles by other means: what lies between the article's tags, cut at its blocks
    want = {}
    for r in pages.collect():
        inside = re.search(r"<article>(.*?)</article>", r["html"], re.S)[1]
        blocks = [" ".join(unescape(re.sub(r"<[^>]*>", " ", b.replace("<b>", "").replace("</b>", ""))).split()) for b in re.split(r"</?(?:p|h1)>", inside)]
        want[r["page_id"], r["url"]] = "\n".join(b for b in blocks if b)
    assert {(r["page_id"], r["url"]): r["text"] for r in out} == want
    twice = html_tree.extract(pages.limit(3).union(pages.limit(3))).collect()
    assert len(twice) == 6 and len({(r["page_id"], r["text"]) for r in twice}) == 3
    assert html_tree.extract(pages.limit(0)).collect() == []


@pytest.mark.parametrize("html, want", [
    ("<article><p title=it's>one</p><p>don't</p><p>two</p></article>", "one\ndon't\ntwo"),
    ("<article><p>&am<b>p;</b> and &lt;b&gt; &amp;amp;</p></article>", "&am p; and <b> &amp;".replace("&am p;", "&amp;")),
    ('<article><p class="x>text</p><p>more words here.</p></article>', "text\nmore words here."),
    ("<article><p>1 < 2 and 3 > 2, a<b>c</b> <3</p></article>", "1 < 2 and 3 > 2, ac <3"),
    ("<article><p a=1 b='>' c=\">\">inside</p><p data-x=a\"b>after</p></article>", "inside\nafter"),
    ("<article><p>one</p><p>the page ends in a tag <a href='", "one\nthe page ends in a tag <a href='"),
])
def test_markup(html, want):
    assert "\n".join(t for _, t in html_tree.parse(html).blocks) == want


@pytest.mark.parametrize("html", ["<p title=it's " * 20_000, "<p title='" * 20_000, "<!" * 20_000, "</" * 20_000, "<a " * 20_000, "<div>" * 20_000, "<blockquote>" * 20_000 + "</section>" * 20_000, "<head>" * 20_000, "<" * 50_000, '<p a="' + "<p b='" * 20_000, "<p>&amp" * 20_000])
def test_hostile_markup_takes_linear_time(html):
    start = time.perf_counter()
    html_tree.trained().texts([html])
    assert time.perf_counter() - start < 5


def test_top_k(spark):
    rng = np.random.default_rng(1)
    rows = [(int(i), [float(x) for x in v]) for i, v in enumerate(rng.normal(0, 0.2, (300, 16)))]
    rows += [(300 + i, rows[7][1]) for i in range(40)]  # ties
    rows += [(400, None), (401, [1.0, None]), (402, [float("nan")] * 16), (403, [float("inf")] * 16), (None, [0.1] * 16), (404, [0.5] * 3), (405, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    found = {}
    for r in top_k(cluttered(df.filter("vec_id % 20 = 0")), cluttered(df), 20).collect():
        found.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    good = [(i, v) for i, v in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    x = np.zeros((len(good), 16))
    for k, (_, v) in enumerate(good):
        x[k, :len(v)] = np.floor(64 * np.array(v, np.float32).astype(float))
    ids = np.array([i for i, _ in good])
    for k, (i, _) in enumerate(good):
        if i % 20 == 0:
            score = x @ x[k]
            order = [j for j in np.lexsort((ids, -score)) if ids[j] != i][:20]
            assert [found[i][r] for r in range(1, 21)] == [(ids[j], score[j]) for j in order]
    assert set(found) == {i for i, _ in good if i % 20 == 0}
    assert top_k(df.limit(0), df, 20).collect() == [] and len(top_k(df.filter("vec_id = 20"), df.filter("vec_id < 3"), 20).collect()) == 3


def test_maxscore_passes_over_blocks():
    rng = np.random.default_rng(3)
    x = rng.integers(-8, 9, (5000, 24)).astype(float)
    x[1000:] = np.floor(x[1000:] / 8)
    q = x[:50] * (rng.random((50, 24)) < 0.4)
    m = MaxScore(np.arange(-50, 0), q, 10)
    for at in range(0, 5000, 500):
        m.feed(np.arange(at, at + 500), x[at:at + 500])
    for i in range(50):
        score = x @ q[i]
        assert m.best[i][0].tolist() == np.lexsort((np.arange(5000), -score))[:10].tolist()
    assert m.passed + m.probed > 0
