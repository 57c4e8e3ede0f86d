"""Thin queries: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .common import read_table
from .decontamination import contaminated
from .mixing import mix_documents
from .near_duplicates import join_texts
from .quality_model import classify
from .quality_rules import judge_documents
from .secrets_scan import scan_documents
from .sharding import shard_documents
from .suffix_dedup import remove_repeats
from .url_filters import judge_pages
from .warc import archive_pages


def op1_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(read_table(spark, sf_dir, "documents")).drop("h")


def op4_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_pages(read_table(spark, sf_dir, "pages"), read_table(spark, sf_dir, "labels"))


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_documents(read_table(spark, sf_dir, "documents"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return archive_pages(read_table(spark, sf_dir, "pages")).drop("archive")


def op7_shard_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(read_table(spark, sf_dir, "documents"))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join_texts(read_table(spark, sf_dir, "documents")).select("doc_id", "class_id", "n_links", "n_copies")


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_documents(read_table(spark, sf_dir, "documents"))


def op10_remove_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(read_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_model": op1_quality_model,
    "op2_decontaminate": op2_decontaminate,
    "op3_mix_sources": op3_mix_sources,
    "op4_url_filters": op4_url_filters,
    "op5_quality_rules": op5_quality_rules,
    "op6_warc": op6_warc,
    "op7_shard_documents": op7_shard_documents,
    "op8_near_duplicates": op8_near_duplicates,
    "op9_secret_scan": op9_secret_scan,
    "op10_remove_repeats": op10_remove_repeats,
}
ORACLES: dict[str, str] = {
    "op6_warc": """
        WITH p AS (
            SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages
        ), f AS (
            SELECT payload_digest, max(page_id) AS first_id FROM p WHERE payload_bytes >= 1000 GROUP BY 1
        )
        SELECT p.page_id, p.payload_bytes, p.payload_digest,
            CASE WHEN p.page_id < f.first_id THEN 'revisit' ELSE 'response' END AS record_type,
            CASE WHEN p.page_id < f.first_id THEN f.first_id END AS refers_to,
            CAST(CASE WHEN p.page_id < f.first_id THEN 1 ELSE greatest(1, ceil(p.payload_bytes / 1048576.0)) END AS INTEGER) AS chunks
        FROM p LEFT JOIN f ON p.payload_digest = f.payload_digest AND p.payload_bytes >= 1000
    """,
}
