"""The registered queries of this subpackage: thin digests of its operators, with production parameters, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import remainder, table

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_collision_counting(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ann import nearest

    return nearest(table(spark, sf_dir, "embeddings"), F.col("id") % 20 == 0)


def op2_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .repeats import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents"), wanted=["n_bytes", "n_removed", "n_spans", "kept_sha256"])


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"), tokenizer("word_bpe_49k.json"))


def op4_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .neighbour_graph import near_duplicate_vectors

    return near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .warc import archived

    return archived(table(spark, sf_dir, "pages"))


def op6_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lm import language_model_scores

    return language_model_scores(table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import fit, quality_scores

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = quality_scores(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", (remainder("doc_id", 4) == 2).alias("held_out"), "score", "predicted")


def op8_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .jaccard import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .byte_bpe import round_trip

    return round_trip(table(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json"))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import cut
    from .mixing import mix, sized

    sizes = cut(sized(table(spark, sf_dir, "documents").select("doc_id", "source", "text")).drop("text"))  # words are counted once
    return mix(sizes).select("doc_id", "size", "source_size", "target", "taken")


QUERIES: dict[str, Query] = {q.__name__: q for q in (op1_collision_counting, op2_suffix_array, op3_token_counts, op4_nn_descent, op5_warc, op6_language_model, op7_quality, op8_ngram_jaccard, op9_byte_bpe, op10_mixing)}

ORACLE_SQL: dict[str, str] = {
    "op5_warc": """
        WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha256(coalesce(html, '')) AS digest FROM pages),
        f AS (SELECT digest, min(page_id) AS first_id FROM p WHERE n >= 100 GROUP BY digest)
        SELECT p.page_id, p.n::BIGINT AS payload_bytes, p.digest AS payload_digest,
            CASE WHEN p.n >= 100 AND p.page_id > f.first_id THEN 'revisit' ELSE 'response' END AS record_type,
            CASE WHEN p.n >= 100 AND p.page_id > f.first_id THEN f.first_id END AS refers_to
        FROM p LEFT JOIN f USING (digest)
    """,
}
