"""The given relational tables as DataFrames."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Least support of a rule in all queries, the one of their SQL; it doesn't depend on the folder.
MIN_SUPPORT = 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows up to which a slim table (rules, slots, masks) is broadcast; beyond that, joins shuffle.
BROADCAST_ROWS = 200_000


def shared_root(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, else the one set on the context; a single machine may do without."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/tempo_rules_checkpoints"
    return root.rstrip("/")


def small(df: DataFrame) -> DataFrame:
    """Marked for broadcast if its rows are counted to be few; `df` should be cheap to read, as written tables are."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def written(df: DataFrame, name: str = "t", partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Cut the lineage: a table in the shared checkpoint folder, read back."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/rules/{uuid.uuid4().hex}/{name}"
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path).select(df.columns)


#: Rows of a bucket, few enough that a task sorts them in memory.
BUCKET_ROWS = 400_000
#: Buckets that are written at a time, so that the shuffle of all rows is never on disk at once.
BUCKETS_AT_ONCE = 50
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def _shuffles_go(spark: SparkSession) -> Iterator[None]:
    """Files of a shuffle go when its query ends, not when the driver next collects garbage."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def bucketed(df: DataFrame, key: str, name: str = "t") -> DataFrame:
    """A table in the shared checkpoint folder whose buckets hold all rows of a key: joins and sums by the key need no exchange.

    Only its plan keeps the table; the catalogue forgets it.
    """
    spark = df.sparkSession
    n = max(1, -(-df.count() // BUCKET_ROWS))
    table_name = f"{name}_{uuid.uuid4().hex}"
    path = f"{shared_root(spark)}/rules/{table_name}"
    bucket = F.pmod(F.hash(key), F.lit(n))
    with _shuffles_go(spark):
        for first in range(0, n, BUCKETS_AT_ONCE):
            part = df.where(bucket.between(first, first + BUCKETS_AT_ONCE - 1)) if n > BUCKETS_AT_ONCE else df
            writer = part.repartition(n, key).write.mode("append").bucketBy(n, key).sortBy(key)
            writer.option("path", path).option("compression", "zstd").format("parquet").saveAsTable(table_name)
    out = spark.table(table_name)
    out.schema  # resolved before the name goes
    spark.sql(f"DROP TABLE {table_name}")
    return out
