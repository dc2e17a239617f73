"""The registered queries of this subpackage: thin, over whole tables, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

import public_tokenizers

from . import bpe, chat, media, mixing, neardup, passages, quality, secretscan, urlfilter, warc
from .common import table

TOKENIZER = public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels"))


def op2_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return secretscan.scan(docs, secretscan.models(docs, table(spark, sf_dir, "labels")))


def op3_warc_index_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = warc.round_trip(table(spark, sf_dir, "pages", "page_id", "url", "html"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "captured")


def op4_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.rates(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels"))


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode(table(spark, sf_dir, "documents", "doc_id", "text"), TOKENIZER, public_tokenizers.PATTERN, with_ids=False)


def op6_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlfilter.judge(table(spark, sf_dir, "pages", "page_id", "url", "html")).select("page_id", "host", "path", "rule", "verdict", "odds")


def op7_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = media.documents_as_media(table(spark, sf_dir, "documents", "doc_id", "text")).filter("kind = 'media'")
    return found.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "position", "caption")


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages.shared_passages(table(spark, sf_dir, "documents", "doc_id", "text"))


def op9_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.classes(table(spark, sf_dir, "documents", "doc_id", "text"), shingle=4)


def op10_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.render(table(spark, sf_dir, "conversations"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_quality_rules,
        op2_secret_scans,
        op3_warc_index_merge,
        op4_source_mixing,
        op5_byte_bpe,
        op6_url_filters,
        op7_media_columns,
        op8_substring_dedup,
        op9_minhash_neardup,
        op10_chat_formatting,
    )
}

#: DuckDB SQL of those queries that SQL can express.
ORACLES: dict[str, str] = {"op9_minhash_neardup": neardup.ORACLE, "op10_chat_formatting": chat.ORACLE}
