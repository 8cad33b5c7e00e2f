"""The queries of this folder: one for each operator, and the pipeline."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.bpe_codec import encode_texts

    return encode_texts(table(spark, sf_dir, "documents"), tokenizer_path())


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.html_tree import extract

    return extract(table(spark, sf_dir, "pages"))


def op3_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.jaccard_join import similar_documents

    return similar_documents(table(spark, sf_dir, "documents"), k=3, num=9, den=10).drop("text_key", "keeper")


def op4_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.topk_search import top_k

    rows = table(spark, sf_dir, "embeddings")
    return top_k(rows.filter("vec_id % 20 = 0"), rows, k=20, scale=64)


OP4_SQL = """
WITH v AS (
    SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS w
    FROM embeddings
    WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
      AND len(list_filter(embedding, lambda x: x IS NOT NULL AND isfinite(x))) = len(embedding)
), s AS (
    SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(q.w::DOUBLE[], c.w::DOUBLE[]) AS BIGINT) AS score
    FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
), r AS (
    SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
) SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.token_counts import section_counts

    return section_counts(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.tiktoken"), rule="most")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def op10_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.fingerprints import compare_with_edits

    return compare_with_edits(table(spark, sf_dir, "documents"))


def op5_source_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm import mixture

    docs = mixture.with_domain(table(spark, sf_dir, "documents"))
    return mixture.mix_documents(docs, mixture.LEVELS, mixture.WEIGHTS, (1, 1), max_epochs=2, seed=17)


def _level_sql(name: str, source: str, path: tuple[str, ...], weight: str) -> str:
    """One level of the budget tree: capacities of a level's nodes, and their shares of what their parent has."""
    level, parents = path[-1], ", ".join(path[:-1]) or "1"
    keys = ", ".join(path)
    order = f"PARTITION BY {parents} ORDER BY CAST(capacity AS DOUBLE) / weight, {level}"
    return f"""
{name}_n AS (
    SELECT {keys}, up, CAST(sum(leaf_tokens) * 2 AS BIGINT) AS capacity, {weight} AS weight FROM {source} GROUP BY {keys}, up
), {name}_f AS (
    SELECT *, capacity * sum(weight) OVER ({order} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)
        <= weight * (up - coalesce(sum(capacity) OVER ({order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS is_full FROM {name}_n
), {name}_l AS (
    SELECT *, up - coalesce(sum(CASE WHEN is_full THEN capacity END) OVER (PARTITION BY {parents}), 0) AS rest_up,
        sum(CASE WHEN NOT is_full THEN weight END) OVER (PARTITION BY {parents}) AS rest_weight FROM {name}_f
), {name} AS (
    SELECT s.* EXCLUDE (up), CAST(CASE WHEN is_full THEN capacity ELSE weight * rest_up // rest_weight END AS BIGINT) AS up FROM {source} s JOIN {name}_l USING ({keys})
)"""


def _case(column: str, weights: dict[str, int]) -> str:
    return f"CASE {column} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in weights.items()) + " ELSE 1 END"


def op5_sql() -> str:
    from treelogic.llm import mixture

    return f"""
WITH rows_ AS (
    SELECT doc_id, 'd' || CAST(coalesce(TRY_CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT), 0) % 4 AS VARCHAR) AS domain, coalesce(lang, '') AS lang, coalesce(source, '') AS source,
        CAST(len(regexp_extract_all(coalesce(text, ''), '[^ \\t\\n\\x0B\\f\\r]+')) AS BIGINT) AS n_tokens FROM documents
), leaves AS (
    SELECT domain, lang, source, CAST(sum(n_tokens) AS BIGINT) AS leaf_tokens FROM rows_ GROUP BY ALL
), base AS (
    SELECT *, (SELECT CAST(sum(leaf_tokens) AS BIGINT) FROM leaves) AS up FROM leaves
),{_level_sql("one", "base", ("domain",), _case("domain", mixture.WEIGHTS["domain"]))},{_level_sql("two", "one", ("domain", "lang"), _case("lang", mixture.WEIGHTS["lang"]))},{_level_sql("three", "two", ("domain", "lang", "source"), "1")},
given AS (
    SELECT *, CASE WHEN leaf_tokens > 0 THEN up // leaf_tokens ELSE 0 END AS whole_, CASE WHEN leaf_tokens > 0 THEN up % leaf_tokens ELSE up END AS rest FROM three
), placed AS (
    SELECT r.*, whole_, rest, coalesce(sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY md5('17:' || CAST(whole_ + 1 AS VARCHAR) || ':' || coalesce(CAST(doc_id AS VARCHAR), 'null')), doc_id, n_tokens ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before_
    FROM rows_ r JOIN given USING (domain, lang, source)
), cut AS (SELECT *, greatest(least(n_tokens, rest - before_), 0) AS part FROM placed)
SELECT doc_id, domain, lang, source, n_tokens, CAST(CASE WHEN n_tokens > 0 THEN whole_ + CASE WHEN part > 0 THEN 1 ELSE 0 END ELSE 0 END AS BIGINT) AS epochs, CAST(whole_ * n_tokens + part AS BIGINT) AS taken_tokens FROM cut
"""


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.lang_ppm import predict_held_out

    return predict_held_out(table(spark, sf_dir, "documents"))


def op7_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.token_store import round_trip

    return round_trip(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from treelogic.llm.substring_dedup import drop_repeats

    return drop_repeats(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_bpe_codec, op2_html_text, op3_ngram_jaccard, op4_topk_search, op5_source_mixture, op6_language_id, op7_token_store, op8_substring_dedup, op9_token_counts, op10_document_fingerprints, pipeline)}


def oracle_sql() -> dict[str, str]:
    return {"op4_topk_search": OP4_SQL, "op5_source_mixture": op5_sql()}
