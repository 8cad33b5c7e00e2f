import collections
import hashlib
import re

import numpy as np
import pyarrow as pa
import pytest

from tests.llm.conftest import ODD, cluttered
from treelogic.llm import jaccard_join
from treelogic.llm.arrowkit import Words
from treelogic.llm.components import components
from treelogic.llm.fingerprints import Sketch, compare_with_edits, fingerprint_documents
from treelogic.llm.jaccard_join import similar_documents
from treelogic.llm.substring_dedup import drop_repeats, sliding_least

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall((text or "").encode())


def test_word_hashes():
    texts = [t for _, t in ODD] + ["tail", "a\tb\x0bc", " x"]
    w = Words(pa.array(texts))
    assert list(w.counts) == [len(words(t)) for t in texts]
    seen = {}
    for word, h in zip([x for t in texts for x in words(t)], w.hash.tolist()):
        assert seen.setdefault(word, h) == h
    assert len(set(seen.values())) == len(seen)
    runs, at = w.runs(3)
    groups = {}
    flat = [x for t in texts for x in words(t)]
    for h, i in zip(runs.tolist(), at.tolist()):
        assert groups.setdefault(h, tuple(flat[i:i + 3])) == tuple(flat[i:i + 3])


def test_sliding_least():
    x = np.random.default_rng(0).integers(0, 100, 50)
    for width in (1, 2, 3, 7, 28, 50, 51):
        want = [x[i:i + width].min() for i in range(max(0, 50 - width + 1))]
        assert sliding_least(x, width).tolist() == want


def brute_classes(rows, k, num, den):
    sets = []
    for _, text in rows:
        w = [x.lower() for x in words(text)]
        sets.append(frozenset(tuple(w[i:i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)]) if w else frozenset())
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    having = collections.defaultdict(list)
    for j, s in enumerate(sets):
        for i, n in collections.Counter(i for t in s for i in having[t]).items():
            if den * n >= num * (len(s) + len(sets[i]) - n):
                parent[find(i)] = find(j)
        for t in s:
            having[t].append(j)
    least = {}
    big = 10**18
    for i, (doc_id, _) in enumerate(rows):
        r = find(i)
        least[r] = min(least.get(r, big), big if doc_id is None else doc_id)
    return collections.Counter((rows[i][0], len(sets[i]), None if least[find(i)] == big else least[find(i)]) for i in range(len(rows)))


@pytest.mark.parametrize("k, num, den", [(3, 9, 10), (5, 4, 5)])
def test_similar_documents(some, k, num, den):
    rows = [(r[0], r[1]) for r in some.collect()]
    found = collections.Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in similar_documents(cluttered(some), k, num, den).collect())
    assert found == brute_classes(rows, k, num, den)


def near_copies(n):
    import random

    r = random.Random(3)
    base = [f"w{r.randint(0, 400)}" for _ in range(120)]
    rows = []
    for i in range(n):
        copy = base[:]
        for _ in range(r.randint(0, 6)):
            copy[r.randrange(len(copy))] = f"z{r.randint(0, 10**6)}"
        rows.append((i, " ".join(copy)))
    passage = " ".join(f"p{i}" for i in range(40))
    rows += [(1000 + i, " ".join(f"u{r.randint(0, 10**6)}" for _ in range(60)) + " " + passage) for i in range(n)]
    return rows


def test_large_family_and_common_passage(spark):
    """Hundreds of near copies and a passage that many documents share."""
    rows = near_copies(150)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = collections.Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in similar_documents(df, 3, 9, 10).collect())
    assert found == brute_classes(rows, 3, 9, 10)


def test_one_keeper_for_each_class(some):
    out = similar_documents(some, 5, 4, 5).collect()
    keepers = collections.Counter(r["component_id"] for r in {(r["doc_id"], r["text_key"], r["component_id"]) and r for r in out} if r["keeper"])
    assert set(keepers) == {r["component_id"] for r in out}
    assert similar_documents(some.limit(0)).collect() == []


def test_threshold_prefix():
    t = jaccard_join.Threshold(9, 10)
    for n in range(1, 200):
        assert t.prefix(n) == n - -(-9 * n // 10) + 1
        assert t.most_apart(2 * n) == (2 * n) // 19


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (102, 101), (5, 5), (200, 300)], "a long, b long")
    found = {r["a"]: r["root"] for r in components(links).collect()}
    assert all(found[i] == 0 for i in range(41)) and found[102] == found[101] == 100 and found[300] == 200
    assert components(links.limit(0)).collect() == []


def brute_repeats(rows, k=35):
    texts = [words(t) for _, t in rows]
    seen = collections.Counter(tuple(w[i:i + k]) for w in texts for i in range(len(w) - k + 1))
    out = collections.Counter()
    for (doc_id, _), w in zip(rows, texts):
        covered = [False] * len(w)
        for i in range(len(w) - k + 1):
            if seen[tuple(w[i:i + k])] > 1:
                covered[i:i + k] = [True] * k
        kept = [x for x, c in zip(w, covered) if not c]
        out[doc_id, len(w), len(w) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()] += 1
    return out


def test_repeats(some):
    rows = [(r[0], r[1]) for r in some.collect()]
    found = collections.Counter(tuple(r) for r in drop_repeats(cluttered(some).select("doc_id", "text", "lo", "hi", "n_words")).collect())
    assert found == brute_repeats(rows) and any(k[2] for k in found)
    assert drop_repeats(some.limit(0)).collect() == []


def test_repeats_of_a_common_passage(spark):
    rows = near_copies(60)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert collections.Counter(tuple(r) for r in drop_repeats(df).collect()) == brute_repeats(rows)


def test_edited_texts(some, odd):
    for df in (some, odd, odd.limit(1), odd.limit(0)):
        rows = sorted(((r[0] is not None, r[0] or 0), r[1] or "") for r in df.collect())
        want = []
        for i, (key, t) in enumerate(rows):
            half = len(t) // 2
            want.append((key, len(t), hashlib.sha256((t[:len(t) - half] + rows[(i + 1) % len(rows)][1][:half]).encode()).hexdigest()))
        got = [((r["doc_id"] is not None, r["doc_id"] or 0), r["n_chars"], r["edited_sha256"]) for r in compare_with_edits(cluttered(df)).collect()]
        assert sorted(got) == sorted(want)


def test_likeness(documents):
    out = compare_with_edits(documents).collect()
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in out)
    assert sum(r["near_edited"] > r["near_next"] for r in out) > 0.9 * len(out)
    same = {}
    for r in fingerprint_documents(documents, keep=("doc_id", "text")).collect():
        assert same.setdefault(r["text"], r["fingerprint"]) == r["fingerprint"]


def test_sketches_merge():
    rng = np.random.default_rng(2)
    a, b = np.unique(rng.integers(0, 2**63, 4000).astype(np.uint64)), np.unique(rng.integers(0, 2**63, 300).astype(np.uint64))
    b = np.union1d(b, a[:300])
    merged = Sketch.of(a).merge(Sketch.of(b))
    whole = Sketch.of(np.union1d(a, b))
    assert np.array_equal(merged.hashes, whole.hashes) and Sketch.parse(merged.text()).text() == merged.text()
    assert abs(Sketch.of(a).containment(Sketch.of(b)) - 0.5) < 0.2
    assert Sketch.of(a[:0]).containment(Sketch.of(a[:0])) == 1.0 and Sketch.of(a[:0]).containment(Sketch.of(a)) == 0.0


def doubling(n, a="a", b="b"):
    """Two words of n letters in the doubling pattern and its complement: sums of powers cannot tell them apart."""
    x, y = a, b
    while len(x) < n:
        x, y = x + y, y + x
    return x, y


@pytest.mark.parametrize("n", [64, 256, 1024, 2048, 4096])
def test_doubling_words_differ(n):
    x, y = doubling(n)
    one, two = Words(pa.array([x, y])).hash.tolist()
    assert one != two
    for k in (16, 32):
        x, y = doubling(2 * k, "a ", "b ")
        runs, _ = Words(pa.array([x, y])).runs(k)
        assert runs[0] != runs[1]


def test_sketch_of_union_is_union_of_sketches():
    rng = np.random.default_rng(4)
    for n in (3, 100, 1000):
        a, b = (np.unique(rng.integers(0, 2**63, n).astype(np.uint64)) for _ in range(2))
        whole = Sketch.of(np.union1d(a, b))
        merged = Sketch.of(a).merge(Sketch.of(b))
        assert merged.scale == whole.scale and np.array_equal(merged.hashes, whole.hashes)
        # sketches of different fractions meet at the smaller one
        mixed = Sketch.of(a, 2).merge(Sketch.of(b, 8))
        assert mixed.text() == Sketch.of(np.union1d(a, b), 8).text()


@pytest.mark.parametrize("min_words, seed_words", [(300, 8), (400, 400), (35, 1), (1, 1), (256, 20)])
def test_long_windows(spark, min_words, seed_words):
    import random

    r = random.Random(7)
    passage = [f"p{r.randint(0, 500)}" for _ in range(700)]
    rows = [(1, " ".join(passage)), (2, " ".join(["x", "y", *passage[100:640], "z"])), (3, " ".join(passage[:290])), (4, "unrelated words"), (5, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert collections.Counter(tuple(r) for r in drop_repeats(df, min_words, seed_words).collect()) == brute_repeats(rows, min_words)
    with pytest.raises(ValueError):
        drop_repeats(df, 5, 6)
