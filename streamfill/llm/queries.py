"""The queries that apply each operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: For these queries only; in production the key comes from a secret store.
PII_KEY = "example key of the test queries"


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard

    return shard(table(spark, sf_dir, "documents"), 8)


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .neardup import hex16, near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", hex16(F.col("fp")).alias("fingerprint"), "component_id")


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .classifier import classify, fit, graded

    docs = table(spark, sf_dir, "documents")
    return classify(docs, fit(*graded(docs, table(spark, sf_dir, "labels"))))


def op4_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .topk import top_k

    return top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, 5)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .tokens import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .packing import pack

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), 1024, with_ids=False).drop("ids", "bucket")


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .bytebpe import encode

    docs = table(spark, sf_dir, "documents")
    return encode(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=False).drop("ids")


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import judge

    return judge(table(spark, sf_dir, "documents")).drop("left_words")


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secrets import scan

    return scan(table(spark, sf_dir, "documents")).drop("findings")


def op10_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import replace_private

    return replace_private(table(spark, sf_dir, "documents"), PII_KEY)


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}


ORACLES = {
    "op4_exact_top_k": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS code
            FROM embeddings
            WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
        ),
        pairs AS (
            SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
                   CAST(list_sum(list_transform(range(1, len(q.code) + 1), lambda i: q.code[i] * c.code[i])) AS BIGINT) AS score
            FROM v q JOIN v c ON c.vec_id <> q.vec_id AND len(c.code) = len(q.code)
            WHERE q.vec_id % 50 = 0
        ),
        ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM pairs)
        SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score FROM ranked WHERE r <= 5
    """,
    "op8_quality_rules": r"""
        WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(source, '') AS host, coalesce(text, '') AS t FROM documents),
        l AS (
            SELECT *, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS raw,
                   list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words
            FROM d
        ),
        n AS (
            SELECT *, list_transform(raw, lambda x: array_to_string(list_filter(regexp_split_to_array(lower(x), '[\x20\x09-\x0D]+'), lambda w: w <> ''), ' ')) AS lines FROM l
        ),
        windows AS (SELECT r, i, words[i:i + 4] AS w FROM (SELECT r, words, unnest(range(1, len(words) - 3)) AS i FROM n)),
        again AS (SELECT r, i, count(*) OVER (PARTITION BY r, w) AS c FROM windows),
        starts AS (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS later FROM again WHERE c > 1),
        repeats AS (SELECT r, CAST(sum(least(5, coalesce(later - i, 5))) AS BIGINT) AS n_repeat_words FROM starts GROUP BY r),
        seen AS (SELECT DISTINCT host, list_sort(list_distinct(lines)) AS document, line FROM (SELECT host, lines, unnest(lines) AS line FROM n)),
        frequent AS (SELECT host, line FROM seen GROUP BY host, line HAVING count(*) > 20),
        removed AS (
            SELECT r, CAST(sum(len(string_split(line, ' '))) AS BIGINT) AS gone
            FROM (SELECT r, host, unnest(lines) AS line FROM n) JOIN frequent USING (host, line) GROUP BY r
        ),
        measured AS (
            SELECT r, doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(list_sum(list_transform(words, lambda x: length(x))) AS BIGINT) AS word_chars,
                   CAST(length(t) - length(translate(t, '#*$%&|<>', '')) AS BIGINT) AS n_symbols,
                   CAST(len(raw) - len(list_distinct(raw)) AS BIGINT) AS n_dup_lines
            FROM n
        ),
        judged AS (
            SELECT m.*, coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(gone, 0) AS gone,
                   n_words < 10 OR 100 * coalesce(n_repeat_words, 0) > 20 * n_words AS base_failed
            FROM measured m LEFT JOIN repeats USING (r) LEFT JOIN removed USING (r)
        )
        SELECT doc_id, n_words, coalesce(word_chars, 0) AS word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
               NOT base_failed AND n_words - gone >= 10 AND n_words - gone >= 0.2 * n_words AS kept
        FROM judged
    """,
}
