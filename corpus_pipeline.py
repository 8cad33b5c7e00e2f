"""The corpus pipeline: five stages over ``documents``, each written and read again.

Every stage but the last returns the columns of documents, whatever they are
called.  A stage's decision goes back to its rows by (doc_id, hash of the text),
so rows that share an id but not a text stay apart.  All stages take null ids,
texts, languages and sources, empty texts and tables, and texts of any length.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treelogic.llm import bpe_codec, jaccard_join, lang_ppm, mixture, substring_dedup
from treelogic.llm.registry import tokenizer_path
from treelogic.llm.shared import drop_folder, shared_folder, shielded

#: Least share of the likelihood that a document's best language must have, and most bits per byte above what is
#: usual in it.  Noisy documents of learned languages (capitals, tables, keys, numbers) stay under 5 on the given
#: tables; text of languages that were not learned, and program text, is over 8.  Texts of few bytes are not judged so.
LEAST_SCORE = 0.5
MOST_EXCESS = 6.5
JUDGED_BYTES = 64
MIX_SHARE = (4, 5)
SEED = 17


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents without a letter, without a language that has most of the likelihood, or in
    none of the learned languages.

    The model is trained on the labelled documents that op6 trains on.  A null or
    empty text has no letter and goes; rows that repeat share their fate; a tie
    between languages leaves less than most of the likelihood and goes.  The
    whole text is scored, however long.
    """
    labelled = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = lang_ppm.train(labelled.filter(~F.coalesce(lang_ppm.held_out(), F.lit(False))))
    rows, names = shielded(docs, "doc_id", "text")
    told = lang_ppm.identify(rows, model, keep=tuple(rows.columns))
    kept = (F.col("lang_pred") != lang_ppm.UNKNOWN) & (F.col("score") >= LEAST_SCORE) & ((F.col("excess") <= MOST_EXCESS) | (F.octet_length("text") < JUDGED_BYTES))
    return told.filter(kept).select(*names)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each class of similar ones (five words, 0.8): the least doc_id.

    A null doc_id counts as the largest.  Of rows that share id and text the first
    stays, in the order of their other columns as text, nulls first.  Null and
    empty texts are similar to nothing: each pair of id and text stays once.
    """
    told = jaccard_join.similar_documents(docs, k=5, num=4, den=5).filter("keeper").select(F.coalesce("doc_id", F.lit(-1)).alias("__id"), F.col("text_key").alias("__key")).distinct()
    rows, names = shielded(docs, "doc_id", "text")
    order = [F.col(c).cast("string").asc_nulls_first() for c in rows.columns if c not in ("doc_id", "text")] or [F.lit(0)]
    rows = rows.withColumn("__id", F.coalesce(F.col("doc_id").cast("long"), F.lit(-1))).withColumn("__key", F.xxhash64("text"))
    first = F.row_number().over(Window.partitionBy("__id", "__key").orderBy(*order))
    return rows.join(told, ["__id", "__key"], "left_semi").withColumn("__n", first).filter("__n = 1").select(*names)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes out every word of a repeated 35-word window; documents that had words and have none left go.

    A text that loses nothing stays as it is; of others the kept words are joined
    by single spaces and ``n_chars`` follows.  Null and empty texts have no words
    and stay.  Rows that repeat as a whole repeat each other's windows.
    """
    rows, names = shielded(docs, "doc_id", "text")
    kept = substring_dedup.drop_repeats(rows, full=True)
    text = F.when(F.col("n_removed") > 0, F.col("kept_text")).otherwise(F.col("text"))
    changed = kept.filter((F.col("n_removed") == 0) | (F.col("n_removed") < F.col("n_words")))
    new = {"text": text, "n_chars": F.char_length(text).cast("long")}
    return changed.select(*[new[c].alias(c) if c in new else column for c, column in zip(docs.columns, names)])


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents taken for the target weights, whole (the last of a source too).

    Null languages and sources are groups of their own; a document without words
    has no tokens to take and goes.  The order inside a source is that of a seeded
    hash of the id, ties by id and tokens; rows that share id and text share
    their fate.
    """
    rows, names = shielded(docs, "doc_id", "text", "lang", "source")
    rows = rows.withColumn("__key", F.xxhash64("text"))
    told = mixture.mix_documents(mixture.with_domain(rows), mixture.LEVELS, mixture.WEIGHTS, MIX_SHARE, max_epochs=1, seed=SEED, keep=("__key",))
    chosen = told.filter("epochs > 0").select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)).alias("__id"), "__key").distinct()
    rows = rows.withColumn("__id", F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)))
    return rows.join(chosen, ["__id", "__key"], "left_semi").select(*names)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids and the decoded text of each document, one row for each input row.

    A null text encodes as an empty one; equal texts have equal digests.
    """
    return bpe_codec.encode_texts(docs, tokenizer_path(), keep=("doc_id", "lang", "source"))


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("mix_sources", mix_sources),
    ("encode", encode),
]

#: The byte model and the digests are outside SQL; tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; what lies between them is written to the shared folder, and deleted there
    once the next stage has been written.  The last one stays, since the result is read from it."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    before = None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            drop_folder(spark, before)
        before = f"{folder}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
