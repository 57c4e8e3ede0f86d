"""Narrowing half-good rules by the classes of the entities that they bind."""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import PREDICATES, SYMMETRIC
from ..plans.kg import KnowledgeGraph, links, temporal_edges
from ..sources.tables import small, written
from .match import match_linked_subjects, match_one_subject, ordered_pairs, time_of
from .mine import CLASSES, MinerConfig, as_constraints
from .score import RULE

#: Column of a match that each class column restricts.
SLOT = {"cx": "x", "cy": "o1", "cz": "o2", "cw": "w"}


def _with_classes(matches: DataFrame, sets: DataFrame, column: str, name: str) -> DataFrame:
    """One row per class of the slot's entity, and one with '*'."""
    known = sets.select(F.col("entity").alias(column), F.col("set").alias(f"{name}_set"))
    values = F.array_union(F.array(F.lit("*")), F.coalesce(f"{name}_set", F.array().cast("array<string>")))
    return matches.join(known, column, "left").withColumn(name, F.explode(values)).drop(f"{name}_set")


def frequent_classes(edges: DataFrame, classes: DataFrame, min_support: int) -> tuple[DataFrame, DataFrame]:
    """Classes (p, d, class) of enough subjects of a slot, and of the objects of enough subjects: no rule restricted to others can have the support."""
    e = edges.select("x", "p", "d", "y").distinct()
    out = []
    for at in ("x", "y"):
        named = e.join(classes.select(F.col("entity").alias(at), "class"), at).select("x", "p", "d", "class").distinct()
        out.append(written(named.groupBy("p", "d", "class").agg(F.count("*").alias("n")).where(F.col("n") >= min_support).drop("n"), "frequent"))
    return out[0], out[1]


def _only_frequent(rows: DataFrame, name: str, n: int, frequent: DataFrame) -> DataFrame:
    """Rows whose class in a column is '*' or frequent in the n-th slot."""
    known = frequent.select(F.col("p").alias(f"p{n}"), F.col("d").alias(f"d{n}"), F.col("class").alias(name), F.lit(True).alias("_frequent"))
    return rows.join(small(known), [f"p{n}", f"d{n}", name], "left").where((F.col(name) == "*") | F.col("_frequent")).drop("_frequent")


def _expanded(matches: DataFrame, rules: DataFrame, key: list[str], kg: KnowledgeGraph, slots: list[str], cfg: MinerConfig, frequent: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    verdict: Column = F.lit(None)
    for h in PREDICATES:
        verdict = F.when(F.col("head") == h, PREDICATES[h](time_of(1), time_of(2))).otherwise(verdict)
    rows = matches.join(small(rules.select("head", "pattern", *key)), key).withColumn("verdict", verdict)
    sets = kg.classes.groupBy("entity").agg(F.collect_set("class").alias("set"))
    for c in slots:
        rows = _with_classes(rows, sets, SLOT[c], c)
        if frequent and c != "cw":
            rows = _only_frequent(rows, c, 2 if c == "cz" else 1, frequent[0] if c == "cx" else frequent[1])
    for c in CLASSES:
        if c not in slots:
            rows = rows.withColumn(c, F.lit("*"))
    # a symmetric rule over one slot has unordered objects: their classes are sorted
    swap = F.col("head").isin(*SYMMETRIC) & (F.col("pattern") == "a_same")
    low, high = F.least("cy", "cz"), F.greatest("cy", "cz")
    rows = rows.withColumns({"cy": F.when(swap, low).otherwise(F.col("cy")), "cz": F.when(swap, high).otherwise(F.col("cz"))})
    return rows.where(" or ".join(f"{c} <> '*'" for c in CLASSES))


def refined_scores(kg: KnowledgeGraph, coarse: DataFrame, cfg: MinerConfig, supported: bool = False) -> DataFrame:
    """Counts of every class-restricted form of coarse rules (never-rules aren't restricted).

    `supported` leaves out forms with classes of fewer subjects than the support, before any
    counts; at entity level none of them can have it, at fact level the option does nothing.
    """
    coarse = written(coarse.where("head <> 'never'"), "coarse")
    e = temporal_edges(kg.facts, cfg.reverse_facts, cfg.drop_inverted)
    slots = [c for c, v in (("cx", "x"), ("cy", "y"), ("cz", "z"), ("cw", "w")) if v in cfg.refine_slots]
    key = ["p1", "d1", "p2", "d2"]
    out = None
    frequent = None
    if supported and cfg.level == "entity":
        used = small(coarse.select(F.col("p1").alias("p"), F.col("d1").alias("d")).union(coarse.select("p2", "d2")).distinct())
        frequent = frequent_classes(e.join(used, ["p", "d"], "left_semi"), kg.classes, cfg.min_support)
    one = coarse.where("pattern <> 'b'")
    if not one.isEmpty():
        pairs = one.select(*key).union(one.select("p2", "d2", "p1", "d1")).distinct()
        matches = match_one_subject(e, None, cfg.distinct_objects, pairs)
        ordered = one.where(F.col("head").isin("before", "include"))
        sym = one.where(F.col("head").isin(*SYMMETRIC))
        own = [c for c in slots if c != "cw"]
        parts = [_expanded(matches, sym, key, kg, own, cfg, frequent), _expanded(ordered_pairs(matches), ordered, key, kg, own, cfg, frequent)]
        out = parts[0].select("head", "pattern", F.lit(None).cast("string").alias("p0"), F.lit(None).cast("tinyint").alias("d0"), *key, *CLASSES, "x", "verdict", "fact1", "fact2")
        more = parts[1].select("head", "pattern", F.lit(None).cast("string").alias("p0"), F.lit(None).cast("tinyint").alias("d0"), *key, *CLASSES, "x", "verdict", "fact1", "fact2")
        out = out.unionByName(more)
    two = coarse.where("pattern = 'b'")
    if not two.isEmpty():
        triples = two.select("p1", "d1", "p0", "d0", "p2", "d2").distinct()
        matches = match_linked_subjects(e, links(kg.facts, cfg.reverse_links), triples)
        rows = _expanded(matches, two, ["p0", "d0", *key], kg, slots, cfg)
        rows = rows.select("head", "pattern", "p0", "d0", *key, *CLASSES, "x", "verdict", "fact1", "fact2")
        out = rows if out is None else out.unionByName(rows)
    if out is None:
        return coarse.select(*RULE, *CLASSES, "n_pos", "n_neg", "n_unk").limit(0)
    count = [F.count_if(F.col("verdict") == v).alias(n) for n, v in (("n_pos", 1), ("n_neg", -1), ("n_unk", 0))]
    if cfg.level == "entity":
        out = out.groupBy(*RULE, *CLASSES, "x").agg(F.min("verdict").alias("verdict"))
    else:
        out = out.select(*RULE, *CLASSES, "fact1", "fact2", "x", "verdict").distinct()
    return out.groupBy(*RULE, *CLASSES).agg(*count)


def refine(kg: KnowledgeGraph, coarse: DataFrame, cfg: MinerConfig, minimal: bool = False) -> DataFrame:
    """Class-restricted rules with enough support and confidence; minimal leaves out those that a wider one implies."""
    scored = as_constraints(refined_scores(kg, coarse, cfg, supported=True), cfg.level, "refined")
    out = scored.where((F.col("support") >= cfg.min_support) & cfg.above(cfg.accept_conf))
    return most_general(written(out, "refined")) if minimal else out


def most_general(rules: DataFrame) -> DataFrame:
    """Rules that no other rule of the table with more wildcards covers: every wider form of a rule is looked up by equality."""
    wider = rules.select("cid", *RULE, *CLASSES)
    for c in CLASSES:
        wider = wider.withColumn(f"w_{c}", F.explode(F.array_distinct(F.array(F.col(c), F.lit("*")))))
    wider = wider.where(" or ".join(f"w_{c} <> {c}" for c in CLASSES)).select("cid", *[F.col(c).alias(f"w_{c}") for c in RULE], *[f"w_{c}" for c in CLASSES])
    on = reduce(and_, [wider[f"w_{c}"].eqNullSafe(rules[c]) for c in (*RULE, *CLASSES)])
    covered = wider.join(rules.select(*RULE, *CLASSES), on, "left_semi").select("cid").distinct()
    return rules.join(covered, "cid", "left_anti")
