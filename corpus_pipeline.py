"""From documents to mixed, deduplicated, clean shards: five stages over whole tables.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; each is written as
Parquet and read again as the next one's docs. Rows are told apart by doc_id and
128 bits of their content, so repeated rows share their decision.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tempo_rules.llm.common import broadcast_if_small, materialize, read_table, text_key
from tempo_rules.llm.decontamination import clean_documents
from tempo_rules.llm.mixing import mix_documents
from tempo_rules.llm.near_duplicates import join_texts
from tempo_rules.llm.quality_rules import kept_documents
from tempo_rules.llm.sharding import assign_shards

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
SHARDS = 16


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the robust distances leave."""
    return kept_documents(docs.select(COLUMNS)).select(COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of equal or similar texts."""
    rows = materialize(join_texts(docs).select("doc_id", "k1", "k2", "is_first"), "classes")
    per_row = rows.groupBy("doc_id", "k1", "k2").agg(F.max("is_first").alias("stays"), F.count("*").alias("n"))
    gone = materialize(per_row.where("not stays").select(F.col("doc_id").alias("g_doc"), "k1", "k2"), "gone")
    k1, k2 = text_key()
    named = docs.select(COLUMNS).withColumns({"k1": k1, "k2": k2})
    gone = broadcast_if_small(gone)
    left = named.join(gone, (named.k1 == gone.k1) & (named.k2 == gone.k2) & named.doc_id.eqNullSafe(gone.g_doc), "left_anti")
    # rows that repeat a document whole stay once; texts without a word aren't copies
    again = per_row.where("stays and n > 1")
    if not again.isEmpty():
        solid = F.col("text").rlike(r"[^\x20\x09-\x0D]")
        left = left.where(solid).dropDuplicates(["doc_id", "k1", "k2"]).unionByName(left.where(~F.coalesce(solid, F.lit(False))))
    return left.select(COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no item of the benchmark."""
    return clean_documents(docs.select(COLUMNS), read_table(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as its source's share of words asks for."""
    mixed = mix_documents(docs)
    h = F.xxhash64("doc_id", "text")
    taken = materialize(mixed.where("copies > 0").select(F.col("doc_id").alias("m_doc"), "h", "copies"), "copies")
    # rows that repeat a document whole pool their copies
    pooled = taken.groupBy("m_doc", "h").agg(F.sum("copies").cast("int").alias("copies"), F.count("*").alias("n"))
    named = docs.select(COLUMNS).withColumn("dh", h)
    if not pooled.where("n > 1").isEmpty():
        named = named.dropDuplicates(["doc_id", "dh"])
    pooled = broadcast_if_small(pooled, taken.count())
    joined = named.join(pooled, (named.dh == pooled.h) & named.doc_id.eqNullSafe(pooled.m_doc))
    return joined.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(COLUMNS)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row in one of 16 shards of nearly equal bytes, with its place there."""
    size = F.octet_length(F.coalesce("text", F.lit(""))) + 1
    keyed = docs.select(*COLUMNS, size.cast("long").alias("size"), F.xxhash64("text").alias("key"), F.xxhash64("doc_id").alias("tie"))
    return assign_shards(keyed, SHARDS).select(*COLUMNS, "size", "shard", "slot")


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("mixing", mixing),
    ("sharding", sharding),
]

#: Robust distances, sampled splitters and alignments have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
