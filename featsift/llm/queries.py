"""Queries over the whole tables, with production parameters, and their SQL where DuckDB can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, embedding_dedup, exact_dedup, minhash_dedup, ngram_lm, packing, quality, sentencepiece_codec, suffix_dedup, toxicity
from .common import table


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_posteriors(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_file("byte_bpe_50k.json"), capacity=1024, separator=0)


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op5_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_vectors(table(spark, sf_dir, "embeddings"))


def op6_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_lm.language_scores(table(spark, sf_dir, "documents"))


def op7_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.near_duplicates(table(spark, sf_dir, "documents"))


def op8_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.codec_digest(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.format_chats(table(spark, sf_dir, "conversations"))


_ALL = (op1_quality, op2_packing, op3_exact_dedup, op4_suffix_dedup, op5_embedding_dedup, op6_language_model, op7_minhash_dedup, op8_sentencepiece, op9_toxicity, op10_chat)
QUERIES = {f.__name__: f for f in _ALL}

ORACLE_SQL = {
    "op3_exact_dedup": r"""
        WITH n AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents),
             g AS (SELECT text_sha256, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY text_sha256)
        SELECT doc_id, keep_id, group_size, doc_id IS NOT DISTINCT FROM keep_id AS kept, text_sha256 FROM n JOIN g USING (text_sha256)
    """,
    "op10_chat": """
        WITH c AS (SELECT conv_id, list({'r': coalesce(role, 'unknown'), 't': coalesce(text, '')} ORDER BY turn NULLS FIRST, coalesce(role, 'unknown'), coalesce(text, '')) AS t
                   FROM conversations WHERE conv_id IS NOT NULL GROUP BY conv_id),
             p AS (SELECT DISTINCT t[1:n] AS t FROM (SELECT t, unnest(range(1, len(t))) AS n FROM c)),
             f AS (SELECT min(conv_id) AS conv_id, t FROM c GROUP BY t)
        SELECT conv_id, len(t) AS n_turns, list_aggregate(list_transform(t, lambda x: '<|' || x.r || '|>' || chr(10) || x.t || '<|end|>' || chr(10)), 'string_agg', '') AS chat
        FROM f WHERE t NOT IN (SELECT t FROM p)
    """,
}
