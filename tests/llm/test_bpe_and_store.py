import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

from tests.llm.conftest import ODD, cluttered
from treelogic.llm.bpe_codec import decode_ids, encode_texts, word_table
from treelogic.llm.segment import library
from treelogic.llm.token_store import BulkEncoder, Shard, WaveletMatrix, documents_of, export, find_token, read_store, round_trip, write_store


def expected(rows, path):
    lib = library(path)
    out = []
    for doc_id, text in rows:
        ids = lib.encode(text or "", add_special_tokens=False).ids
        out.append((doc_id, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    return out


def by_id(rows):
    return sorted(rows, key=lambda r: (r[0] is not None, r))


def test_codec_equals_library(some, path):
    rows = [(r[0], r[1]) for r in some.collect()]
    found = encode_texts(cluttered(some), path)
    assert found.columns[:4] == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    assert sorted(map(str, found.collect())) == sorted(str(r) for r in found.sparkSession.createDataFrame(expected(rows, path), found.schema).collect())
    assert encode_texts(some.limit(0), path).collect() == []


def test_programme_on_random_words(path):
    r = random.Random(4)
    table, lib = word_table(path), library(path)
    for _ in range(30):
        text = " ".join("".join(r.choice("aabcdeistrn'gé.1") for _ in range(r.randint(1, 25))) for _ in range(200))
        ids = [int(x) for x in table.text(text)[0].split()]
        assert ids == lib.encode(text, add_special_tokens=False).ids


def test_full_output_and_decode(odd, path):
    full = encode_texts(odd, path, full=True)
    rows = decode_ids(full, path, into="again").collect()
    assert all(r["decoded"] == r["again"] for r in rows)


def test_bulk_encoder(path):
    coder, lib = BulkEncoder(path), library(path)
    texts = [t for _, t in ODD] + ["ABC ÀÉß×÷ 12a3 !?a", "ÿþ Þ", "<| a |>"]
    for end in (1, None):
        for _ in range(2):
            ids, offsets = coder.encode(pa.array(texts), end)
            for i, t in enumerate(texts):
                assert ids[offsets[i]:offsets[i + 1]].tolist() == lib.encode(t or "", add_special_tokens=False).ids + ([1] if end else [])


@pytest.mark.parametrize("n, top", [(0, 5), (1, 1), (5, 1), (3000, 49408), (5000, 7), (1025, 70000)])
def test_wavelet_matrix(n, top):
    x = np.random.default_rng(n).integers(0, top, n).astype(np.uint32)
    w = WaveletMatrix.build(x)
    assert (w.tokens() == x).all()
    for t in {*x[:5].tolist(), 0, top + 3}:
        at = np.flatnonzero(x == t)
        assert (w.occurrences(t) == at).all() and w.count(t) == len(at) and w.rank(t, n // 2) == (x[:n // 2] == t).sum()
        if len(at):
            assert w.select(t, len(at) - 1) == at[-1]
    if n:
        places = np.random.default_rng(1).integers(0, n, 40)
        assert (w.access(places) == x[places]).all()
    with pytest.raises(IndexError):
        w.access([n])


def test_round_trip(some, path):
    lib = library(path)
    rows = []
    for doc_id, text in some.collect():
        rows.append((doc_id, np.array([*lib.encode(text or "", add_special_tokens=False).ids, 1], "<u4")))
    rows.sort(key=lambda r: (r[0] is not None, r[0] or 0, r[1].astype("<u2").tobytes()))
    want, at = [], 0
    for doc_id, ids in rows:
        want.append((doc_id, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    found = [tuple(r) for r in round_trip(cluttered(some), path).collect()]
    assert by_id(found) == by_id(want)
    assert round_trip(some.limit(0), path).collect() == []


def test_shards_and_lookup(odd, path, tmp_path, spark):
    write_store(odd, path, str(tmp_path / "store"), shard_tokens=50)
    store = read_store(spark, str(tmp_path / "store"))
    assert store.count() > 3 and documents_of(store).count() == len(ODD)
    assert export(store, str(tmp_path / "files")) == store.count()
    shard = Shard(next((tmp_path / "files").iterdir()).read_bytes())
    assert sum(len(t) for _, t in shard.documents()) == shard.n_tokens
    assert find_token(store, 1).groupBy().sum("occurrences").first()[0] == len(ODD)


def test_words_that_share_a_hash(path, monkeypatch):
    """The store's ids do not rest on hashes: here all words of a length have the same one."""
    from treelogic.llm import arrowkit

    lib = library(path)
    a, b = "a", "b"
    while len(a) < 2048:
        a, b = a + b, b + a
    texts = [a + " the cat", b + " the dog", "cat sat", "tac", "cat act", "the mat " * 30, b, a]
    for weak in (False, True):
        if weak:
            monkeypatch.setattr(arrowkit, "EXACT_BYTES", 0)
            monkeypatch.setattr(arrowkit, "hash_spans", lambda data, start, stop: ((stop - start) % 3).astype(arrowkit.U64))
        coder = BulkEncoder(path)
        for part in (texts, texts[::-1], texts[2:5]):
            ids, offsets = coder.encode(pa.array(part), 1)
            for i, t in enumerate(part):
                assert ids[offsets[i]:offsets[i + 1]].tolist() == lib.encode(t, add_special_tokens=False).ids + [1]


def test_state_of_one_operator_at_a_time():
    from treelogic.llm import arrowkit

    arrowkit._claim("one")
    assert arrowkit.kept("x", lambda: 1) == 1 and arrowkit.kept("x", lambda: 2) == 1
    arrowkit._claim("one")
    assert arrowkit.kept("x", lambda: 3) == 1
    arrowkit._claim("two")
    assert arrowkit.kept("x", lambda: 4) == 4


def test_full_word_table_keeps_frequent_words_and_ids(path, monkeypatch):
    from treelogic.llm import bpe_codec

    monkeypatch.setattr(bpe_codec, "KEPT_WORDS", 20)
    table, lib = bpe_codec.WordTable(path), library(path)
    for i in range(60):
        text = "often " + " ".join(f"rare{chr(97 + (i + j) % 26)}{chr(97 + j)}{i}" for j in range(15)) + " often"
        ids, _, n = table.text(text)
        assert ids == " ".join(map(str, lib.encode(text, add_special_tokens=False).ids)) and n == ids.count(" ") + 1
        assert len(table) <= 10 and len(table.former) <= 10
        assert "often" in table or "often" in table.former
