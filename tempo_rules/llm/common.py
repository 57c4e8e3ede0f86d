"""Shared helpers: reading tables, shared scratch tables, Arrow passes."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Rows handed to Python at once; texts may be long, so a batch stays small.
BATCH_ROWS = 1000
#: Slim rows (about 100 bytes each in memory) up to which a table is broadcast.
BROADCAST_ROWS = 500_000


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """A new folder under the shared checkpoint folder of the session: spark.checkpoint.dir, else the one set on the context.

    Only a session of a single machine (tests) falls back to a local one.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/tempo_rules_checkpoints"
    return f"{root.rstrip('/')}/tables/{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str = "t") -> DataFrame:
    """Cut the lineage: write a table to the shared folder and read it back."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete scratch tables that no later plan reads."""
    for t in tables:
        path = getattr(t, "scratch_path", None)
        if path:
            jvm = t.sparkSession._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(t.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def arrow_pass(
    df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterable[pa.RecordBatch]], schema: str | StructType
) -> DataFrame:
    """mapInArrow with batches of a bounded number of rows; memory goes back when a task ends.

    Where the session has no number of its own, BATCH_ROWS becomes it; bytes of a batch
    are bounded by Spark itself (spark.sql.execution.arrow.maxBytesPerBatch).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fn(batches)
        pa.default_memory_pool().release_unused()

    spark = df.sparkSession
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark.conf.get(key, None) is None:
        spark.conf.set(key, str(BATCH_ROWS))
    return df.mapInArrow(run, schema)


def broadcast_if_small(table: DataFrame, rows: int | None = None) -> DataFrame:
    """Marked for broadcast if it has at most BROADCAST_ROWS slim rows; beyond that, joins shuffle."""
    n = table.count() if rows is None else rows
    return F.broadcast(table) if n <= BROADCAST_ROWS else table


def rebatched(batches: Iterable[pa.RecordBatch], rows: int = 50_000, size: int = 1 << 25) -> Iterator[pa.Table]:
    """Join small batches into tables of about this many rows or bytes, whichever comes first."""
    held: list[pa.RecordBatch] = []
    n = held_bytes = 0
    for b in batches:
        if b.num_rows:
            held.append(b)
            n += b.num_rows
            held_bytes += b.nbytes
        if n >= rows or held_bytes >= size:
            yield pa.Table.from_batches(held).combine_chunks()
            held, n, held_bytes = [], 0, 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def runs(batches: Iterable[pa.RecordBatch], keys: list[str], rows: int = 50_000) -> Iterator[pa.Table]:
    """Tables cut at changes of key, from a stream sorted by these keys.

    Every key's rows come in one table; callers bound the rows of a key.
    """
    import numpy as np

    rest: pa.Table | None = None
    for t in rebatched(batches, rows):
        t = t if rest is None else pa.concat_tables([rest, t]).combine_chunks()
        changed = np.zeros(max(0, t.num_rows - 1), bool)
        for k in keys:
            col = t.column(k).to_numpy()
            changed |= col[1:] != col[:-1]
        cuts = np.flatnonzero(changed)
        if not len(cuts):
            rest = t
            continue
        at = int(cuts[-1]) + 1
        yield t.slice(0, at)
        rest = t.slice(at)
    if rest is not None and rest.num_rows:
        yield rest


def text_key() -> tuple:
    """128 bits that stand for a text: two independent 64-bit hashes."""
    return F.xxhash64("text"), F.xxhash64(F.lit("second"), "text")
