import pytest

#: Rows that every operator on documents must take: nulls, empty texts, ties, repeated rows, odd characters.
ODD = [
    (100001, "a b " * 60), (100001, "a b " * 60), (100002, None), (100003, ""), (100003, "x y"), (100004, "   "), (100005, "X y"),
    (None, "q " * 40), (100006, "日本語 テスト ½ x² <|endoftext|> 's it's ÉTÉ İ ǅ don'T ... !!!"), (100007, "long " + "word" * 5000), (100008, "0123 456 !?"), (5, "again another text"),
]


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string")


@pytest.fixture(scope="session")
def documents(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@pytest.fixture(scope="session")
def some(documents, odd):
    """The small table and the odd rows."""
    return documents.select("doc_id", "text").union(odd)


@pytest.fixture(scope="session")
def path():
    import public_tokenizers

    return str(public_tokenizers.path("word_bpe_49k.json"))


def cluttered(df):
    """The table with extra columns whose names the operators use themselves."""
    from pyspark.sql import functions as F

    for c in ("n_tokens", "part", "key", "text_key", "score", "lang_pred", "n_words", "kept_text", "lo", "hi", "component_id", "bucket", "epochs", "__key", "fingerprint"):
        df = df.withColumn(c, F.lit("x"))
    return df
