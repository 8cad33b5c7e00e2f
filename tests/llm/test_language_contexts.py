"""Nothing is capped but the training rows: languages, contexts, and a choice that does not depend on the dealing."""

import numpy as np
import pyarrow as pa

from tests.llm.test_language_html_search import brute_bits
from treelogic.llm import lang_ppm


def test_little_language_beside_a_big_one():
    r = np.random.default_rng(3)
    texts = {"big": [bytes(r.integers(97, 103, 4000, dtype=np.uint8))], "little": [b"xyz zyx xzy yxz xyz zyx"]}
    model = lang_ppm.fit(texts)
    column = pa.array(["xyz xyz", "abcabc", ""])
    found, _ = model.totals(column)
    for i, t in enumerate(column.to_pylist()):
        assert np.allclose(found[i], brute_bits(model, texts, t.encode()), atol=1e-3)


def test_more_than_64_languages(spark):
    rows = [(i * 10 + j, f"l{i:03d}", "".join(chr(0x400 + i * 3 + (j + n) % 3) for n in range(60)) + " abc") for i in range(90) for j in range(4)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    model = lang_ppm.train(df)
    assert len(model.languages) == 90
    told = lang_ppm.identify(df, model, keep=("lang",)).collect()
    assert all(r["lang"] == r["lang_pred"] for r in told)


def test_blocks_and_texts_do_not_matter():
    r = np.random.default_rng(5)
    text = bytes(r.integers(97, 110, 2 * lang_ppm._BLOCK + 77, dtype=np.uint8)).decode()
    model = lang_ppm.fit({"a": [text[:5000].encode()], "b": [text[-3000:].upper().encode()]})
    whole, _ = model.totals(pa.array(["x", text, "abc"]))
    alone, _ = model.totals(pa.array([text]))
    assert np.allclose(whole[1], alone[0]) and np.allclose(whole[2], model.totals(pa.array(["abc"]))[0][0])


def test_choice_of_training_rows(spark):
    rows = [(i % 700, "en" if i % 3 else "fr", f"text {i} " * (i % 40)) for i in range(3000)] + [(None, "en", "x"), (1, None, "y"), (2, "fr", None)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")

    def chosen(n):
        return sorted(map(tuple, lang_ppm.training_rows(df.repartition(n), 50, 9000).collect()))

    one = chosen(1)
    assert one == chosen(7)
    for lang in ("en", "fr"):
        mine = [t for x, _, t in one if x == lang]
        assert 0 < len(mine) <= 50 and sum(len(t) for t in mine[:-1]) < 9000
    assert lang_ppm.training_rows(df.limit(0)).collect() == []
