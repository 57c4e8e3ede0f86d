"""Matching rule bodies: pairs of temporal facts of one subject, or of two linked subjects."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.granule import TIME_COLUMNS, Interval
from ..functions.predicates import PREDICATES
from ..plans.kg import temporal_edges
from ..sources.tables import small, written

#: Heads that fit a pattern (fixed by the method).
HEADS_FOR = {
    "a_same": ("disjoint", "never", "start", "finish", "before", "include"),
    "a_diff": ("start", "finish", "before", "include"),
    "b": ("start", "finish", "before", "include"),
}


def heads_for(pattern: str) -> tuple[str, ...]:
    return HEADS_FOR[pattern]


def side(edges: DataFrame, n: int, subject: str = "x", value: str = "o") -> DataFrame:
    """Edges as the n-th atom of a body: slot p{n}, d{n}, object, fact and time columns with a prefix."""
    cols = [F.col(c).alias(f"t{n}_{c}") for c in TIME_COLUMNS]
    return edges.select(F.col("x").alias(subject), F.col("p").alias(f"p{n}"), F.col("d").alias(f"d{n}"), F.col("y").alias(f"{value}{n}"), F.col("fact_id").alias(f"fact{n}"), *cols)


def slot(n: int) -> Column:
    return F.struct(f"p{n}", f"d{n}")


def observed_patterns(edges: DataFrame) -> DataFrame:
    """Pairs of slots that some subject has, how many subjects, and how many pairs of facts: p1, d1, p2, d2, n_subjects, n_pairs.

    Works on the set of slots of each subject, which is small, not on its facts.
    """
    per = edges.groupBy("x", "p", "d").agg(F.count("*").alias("n"))
    a = per.select("x", F.col("p").alias("p1"), F.col("d").alias("d1"), F.col("n").alias("n1"))
    b = per.select("x", F.col("p").alias("p2"), F.col("d").alias("d2"), F.col("n").alias("n2"))
    same = slot(1) == slot(2)
    ok = (slot(1) < slot(2)) | (same & (F.col("n1") > 1))
    pairs = F.when(same, F.expr("cast(n1 * (n1 - 1) div 2 as decimal(38,0))")).otherwise(F.expr("cast(n1 * n2 as decimal(38,0))"))
    return a.join(b, "x").where(ok).groupBy("p1", "d1", "p2", "d2").agg(F.count("*").alias("n_subjects"), F.sum(pairs).alias("n_pairs"))


def frequent_pairs(edges: DataFrame, min_support: int, level: str = "entity") -> DataFrame:
    """Slot pairs that enough subjects share (or pairs of facts, at fact level); no rule over others can have the support."""
    n = "n_subjects" if level == "entity" else "n_pairs"
    return observed_patterns(edges).where(F.col(n) >= min_support).select("p1", "d1", "p2", "d2")


def match_one_subject(edges: DataFrame, same_property: bool | None = None, distinct_objects: bool = True, pairs: DataFrame | None = None) -> DataFrame:
    """Unordered pairs of temporal facts of a subject, slot 1 at or below slot 2.

    same_property True or False restricts to equal or different slots; `pairs` to listed
    slot pairs, others are then never formed. The join stays partitioned by subject, so
    aggregation by subject needs no further exchange.
    """
    same = (slot(1) == slot(2)) & (F.col("fact1") < F.col("fact2"))
    diff = (slot(1) < slot(2)) & (F.col("fact1") != F.col("fact2"))
    on = {True: same, False: diff, None: same | diff}[same_property]
    if pairs is not None:
        return match_alive(edges, written(pairs.where(slot(1) <= slot(2)).distinct(), "pairs"), distinct_objects).where(on)
    out = side(edges, 1).join(side(edges, 2), "x").where(on)
    return out.where("o1 <> o2") if distinct_objects else out


def match_alive(edges: DataFrame, alive: DataFrame, distinct_objects: bool = True) -> DataFrame:
    """Pairs of the listed slot pairs only (p1, d1, p2, d2 and further columns): no other pair is ever formed.

    Each fact is sent to its few partner slots, and the join is by subject and slot;
    aggregation by subject and slots needs no further exchange.
    """
    a = side(edges, 1).join(small(alive), ["p1", "d1"])
    ordered = "(fact1 < fact2 or not (p1 = p2 and d1 = d2)) and fact1 <> fact2"
    out = a.join(side(edges, 2), ["x", "p2", "d2"]).where(ordered)
    return out.where("o1 <> o2") if distinct_objects else out


def match_linked_subjects(edges: DataFrame, link_edges: DataFrame, triples: DataFrame | None = None, others: DataFrame | None = None) -> DataFrame:
    """x has fact 1, is linked to another subject w, which has fact 2: ordered pairs.

    With `triples` (p1, d1, p0, d0, p2, d2 and further columns; a written table) each fact is
    sent along its few triples only, and no other pair is ever formed. `others` are the
    edges that fact 2 comes from, if not the same.
    """
    a, b = side(edges, 1), side(edges if others is None else others, 2, "w")
    l = link_edges.select("x", "p0", "d0", F.col("y").alias("w"), "link_fact").where("x <> w")
    if triples is None:
        return a.join(l, "x").join(b, "w").where("fact1 <> fact2")
    return a.join(small(triples), ["p1", "d1"]).join(l, ["x", "p0", "d0"]).join(b, ["w", "p2", "d2"]).where("fact1 <> fact2")


def frequent_triples(edges: DataFrame, link_edges: DataFrame, min_support: int) -> DataFrame:
    """Slot triples (1, link, 2) that enough first subjects have, from the subjects' slot sets."""
    per = edges.select("x", "p", "d").distinct()
    a = per.select("x", F.col("p").alias("p1"), F.col("d").alias("d1"))
    b = per.select(F.col("x").alias("w"), F.col("p").alias("p2"), F.col("d").alias("d2"))
    hop = link_edges.where("x <> y").select("x", "p0", "d0", F.col("y").alias("w")).join(b, "w").select("x", "p0", "d0", "p2", "d2").distinct()
    return a.join(hop, "x").groupBy("p1", "d1", "p0", "d0", "p2", "d2").agg(F.count("*").alias("n")).where(F.col("n") >= min_support).drop("n")


def time_of(n: int) -> Interval:
    return Interval.columns(f"t{n}_")


def with_verdict(matches: DataFrame, head: str, first: int = 1, second: int = 2, same_granule: str = "equal") -> DataFrame:
    return matches.withColumn("verdict", PREDICATES[head](time_of(first), time_of(second), same_granule))


def ordered_pairs(matches: DataFrame) -> DataFrame:
    """Each unordered pair in both orders."""
    swap = {c: c.replace("1", "#").replace("2", "1").replace("#", "2") for c in matches.columns}
    return matches.unionByName(matches.select([F.col(c).alias(swap[c]) for c in matches.columns]))


def match(kg, pattern: str, **options) -> DataFrame:
    if pattern not in HEADS_FOR:
        raise ValueError(f"no pattern {pattern}")
    e = temporal_edges(kg.facts)
    if pattern == "b":
        from ..plans.kg import links

        return match_linked_subjects(e, links(kg.facts), **options)
    return match_one_subject(e, pattern == "a_same", **options)
