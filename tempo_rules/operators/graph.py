"""Connected parts of a graph around given entities, and extraction by property or neighbourhood."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import small, written


def component_of(facts: DataFrame, seeds: DataFrame, max_hops: int | None = None) -> DataFrame:
    """Facts between resources that are connected with a seed (column entity), within max_hops if given.

    The frontier grows hop by hop. An edge leads from a hop to the one before, itself or the
    next one, so new entities are told by the last two hops alone, and each is written once.
    """
    pairs = written(facts.where("o_kind = 'res'").select(F.col("s").alias("a"), F.col("o").alias("b")).distinct(), "pairs")
    both = pairs.union(pairs.select("b", "a"))
    fronts = [written(seeds.select("entity").distinct(), "front")]
    while max_hops is None or len(fronts) <= max_hops:
        step = both.join(fronts[-1], both.a == fronts[-1].entity, "left_semi").select(F.col("b").alias("entity")).distinct()
        for known in fronts[-2:]:
            step = step.join(known, "entity", "left_anti")
        front = written(step, "front")
        if front.isEmpty():
            break
        fronts.append(front)
    reached = reduce(DataFrame.union, fronts)
    return facts.join(reached, facts.s == reached.entity, "left_semi")


def temporal_properties(facts: DataFrame) -> DataFrame:
    """p, n, n_temporal of every property."""
    return facts.groupBy("p").agg(F.count("*").alias("n"), F.count_if("is_temporal").alias("n_temporal"))


def extract_by_properties(facts: DataFrame, properties: DataFrame) -> DataFrame:
    """Facts of the listed properties (column p)."""
    return facts.join(small(properties.select("p").distinct()), "p", "left_semi")


def one_hop(facts: DataFrame, properties: DataFrame) -> DataFrame:
    """All facts of the entities that the listed properties describe."""
    seeds = extract_by_properties(facts, properties).select("s").distinct()
    return facts.join(seeds, "s", "left_semi")


def align(facts: DataFrame, entity_map: DataFrame) -> DataFrame:
    """Facts with subjects and objects renamed by a table (a, b); names not in it stay."""
    m = lambda c: entity_map.select(F.col("a").alias(f"{c}_a"), F.col("b").alias(f"{c}_b"))
    out = facts.join(m("s"), facts.s == F.col("s_a"), "left").join(m("o"), F.col("o") == F.col("o_a"), "left")
    return out.withColumns({"s": F.coalesce("s_b", "s"), "o": F.coalesce("o_b", "o")}).select(facts.columns)
