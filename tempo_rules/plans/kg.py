"""A knowledge graph as two DataFrames: facts and classes.

facts: fact_id, s, p, o, o_kind ('res' or 'lit'), six time columns, is_temporal, src
classes: entity, class
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.granule import TIME_COLUMNS, Interval, is_inverted

FACTS = ("fact_id", "s", "p", "o", "o_kind", *TIME_COLUMNS, "is_temporal", "src")
SCHEMA = (
    "fact_id string, s string, p string, o string, o_kind string, ts_lo long, ts_hi long, ts_gran tinyint, "
    "te_lo long, te_hi long, te_gran tinyint, is_temporal boolean, src string"
)


@dataclass(frozen=True)
class KnowledgeGraph:
    facts: DataFrame
    classes: DataFrame


def edges(facts: DataFrame, reverse: bool = True) -> DataFrame:
    """Facts as edges from x: forward (d = 1) and, for resource objects, backward (d = -1)."""
    rest = ["p", "o_kind", *TIME_COLUMNS, "is_temporal", "src", "fact_id"]
    ahead = facts.select(F.col("s").alias("x"), F.col("o").alias("y"), F.lit(1).cast("tinyint").alias("d"), *rest)
    if not reverse:
        return ahead
    back = facts.where("o_kind = 'res'").select(F.col("o").alias("x"), F.col("s").alias("y"), F.lit(-1).cast("tinyint").alias("d"), *rest)
    return ahead.unionByName(back)


def temporal_edges(facts: DataFrame, reverse: bool = False, drop_inverted: bool = True, cut: DataFrame | None = None) -> DataFrame:
    """Edges that carry an interval; `cut` lists slots (p, d) that are left out."""
    out = edges(facts.where("is_temporal"), reverse)
    if drop_inverted:
        out = out.where(~is_inverted(Interval.columns()))
    if cut is not None:
        out = out.join(F.broadcast(cut), ["p", "d"], "left_anti")
    return out


def links(facts: DataFrame, reverse: bool = True) -> DataFrame:
    """Edges between resources, without their times: x, p0, d0, y and one fact that says so."""
    both = edges(facts.where("o_kind = 'res'"), reverse)
    return both.groupBy("x", F.col("p").alias("p0"), F.col("d").alias("d0"), "y").agg(F.min("fact_id").alias("link_fact"))


def lookup(facts: DataFrame, s: str | None = None, p: str | None = None, o: str | None = None, at: int | None = None) -> DataFrame:
    """Facts that fit a quadruple pattern; `at` keeps those that may hold at that time."""
    out = facts
    for name, value in (("s", s), ("p", p), ("o", o)):
        if value is not None:
            out = out.where(F.col(name) == value)
    if at is not None:
        out = out.where(F.coalesce(F.col("ts_lo") <= at, F.lit(True)) & F.coalesce(F.col("te_hi") > at, F.lit(True)) & F.col("is_temporal"))
    return out


def dictionary_encode(facts: DataFrame) -> DataFrame:
    """Names as 64-bit ids: what a graph of many terabytes stores instead of strings."""
    return facts.withColumns({c: F.xxhash64(c) for c in ("fact_id", "s", "o")})


def tidy(facts: DataFrame, unit: str = "month") -> DataFrame:
    """Facts as earlier datasets have them: none with an absent bound, all of one granularity."""
    from ..functions.granule import granule_of

    whole = facts.where("ts_lo is not null and te_lo is not null")
    at = lambda c: F.timestamp_micros(F.col(c))
    now = Interval(granule_of(at("ts_lo"), unit), granule_of(at("te_lo"), unit))
    return whole.withColumns(dict(zip(TIME_COLUMNS, [c for c in now.named()])))
