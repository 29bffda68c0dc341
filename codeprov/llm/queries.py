"""The queries ``opN_<name>`` over the given tables, and DuckDB SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codeprov.llm import bpe, decontaminate, langid, lcp, lm, packing, pii, simhash, suffixes, urls
from codeprov.llm.common import table


def op1_pack_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode(table(spark, sf_dir, "documents")).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents"))


def op4_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_url_list_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    out = urls.evaluate(urls.example_captures(pages), urls.example_entries(pages))
    return out.select("page_id", "url", "host", F.date_format("fetched_at", "yyyy-MM-dd").alias("fetched_on"), "n_active", "entry", "blocked")


def op6_lcp_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lcp.compare_with_edits(table(spark, sf_dir, "documents"))


def op7_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(pii.detect(table(spark, sf_dir, "documents")))


def op8_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score(table(spark, sf_dir, "documents"))


def op9_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.repeated_passages(table(spark, sf_dir, "documents"))


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_pack_sequences,
        op2_byte_bpe,
        op3_language_id,
        op4_simhash_dedup,
        op5_url_list_filter,
        op6_lcp_fingerprint,
        op7_pii_spans,
        op8_lm_score,
        op9_repeated_passages,
        op10_decontaminate,
    )
}
SQL: dict[str, str] = {"op5_url_list_filter": urls.SQL}
