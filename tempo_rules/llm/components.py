"""Connected components of an edge table by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, release

MAX_ROUNDS = 60
#: Edges of a part of a written table: tables of few edges have few files.
PART_ROWS = 500_000


def _digest(edges: DataFrame) -> tuple:
    mixed = F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40))
    return tuple(edges.agg(F.count("*"), F.sum(mixed)).first())


def components(edges: DataFrame) -> DataFrame:
    """From undirected edges (u, v) of longs: rows (node, root), root the least node of the component.

    Nodes without an edge don't appear; loops are ignored. Each round halves paths,
    so the number of rounds follows the logarithm of the longest of them.
    """
    now = materialize(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    was, before = now, _digest(now)
    for _ in range(MAX_ROUNDS):
        # every neighbour above a node goes to the least of the node's neighbourhood
        both = now.select("u", "v").union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.first("u"), F.min("v")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        # every neighbour below a node, and the node, go to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        # a round doesn't add edges
        now = materialize(small.distinct().coalesce(before[0] // PART_ROWS + 1), "edges")
        release(was)
        was, after = now, _digest(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components didn't settle")
    roots = now.select(F.col("v").alias("node")).distinct().withColumn("root", F.col("node"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots)
