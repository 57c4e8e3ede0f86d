"""Conflicts: pairs of facts that violate a rule. They are reported, not resolved."""

from __future__ import annotations

import json
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.granule import TIME_COLUMNS, Interval, is_inverted
from ..functions.predicates import PREDICATES, SYMMETRIC
from ..plans.kg import KnowledgeGraph, links, temporal_edges
from ..sources.tables import small
from .match import side, time_of
from .mine import CLASSES, CONSTRAINTS

CONFLICTS = ("cid", "x", "fact1", "fact2", "link_fact", "verdict")


class _Shape:
    """What a rule table uses: heads, whether it links subjects, whether it restricts classes. The table is small."""

    def __init__(self, rules: DataFrame) -> None:
        plain = " and ".join(f"{c} = '*'" for c in CLASSES)
        rows = rules.select("head", F.expr("pattern = 'b'").alias("linked"), F.expr(f"not ({plain})").alias("narrow")).distinct().collect()
        self.heads = sorted({r[0] for r in rows})
        self.linked = any(r[1] for r in rows)
        self.one = any(not r[1] for r in rows)
        self.narrow = any(r[2] for r in rows)


def _violated(shape: _Shape) -> Column:
    out: Column = F.lit(None)
    for h in shape.heads:
        v = F.lit(-1) if h == "never" else PREDICATES[h](time_of(1), time_of(2))
        out = F.when(F.col("head") == h, v).otherwise(out) if len(shape.heads) > 1 else v
    return out.cast("tinyint")


def _unordered() -> Column:
    """Rules over one slot whose head doesn't mind the order: each pair once."""
    return F.col("head").isin(*SYMMETRIC, "never") & (F.col("p1") == F.col("p2")) & (F.col("d1") == F.col("d2"))


def _restricted(pairs: DataFrame, kg: KnowledgeGraph) -> DataFrame:
    """Keep matches whose entities have the classes that the rule asks for."""
    plain = " and ".join(f"{c} = '*'" for c in CLASSES)
    open_, narrow = pairs.where(plain), pairs.where(f"not ({plain})")
    two = F.col("pattern") == "b"
    entity = {"cx": F.col("x"), "cy": F.col("o1"), "cz": F.col("o2"), "cw": F.when(two, F.col("w")).otherwise(F.col("x"))}
    swapped = _unordered()
    fits = {}
    for c in ("cx", "cy", "cz", "cw"):
        for flip in ("", "_flip") if c in ("cy", "cz") else ("",):
            at = entity[{"cy": "cz", "cz": "cy"}.get(c, c)] if flip else entity[c]
            has = kg.classes.select(F.col("entity").alias(f"e_{c}{flip}"), F.col("class").alias(f"k_{c}{flip}"))
            narrow = narrow.join(has, (at == F.col(f"e_{c}{flip}")) & (F.col(c) == F.col(f"k_{c}{flip}")), "left")
            fits[c + flip] = (F.col(c) == "*") | F.col(f"e_{c}{flip}").isNotNull()
    ok = fits["cx"] & fits["cw"] & ((fits["cy"] & fits["cz"]) | (swapped & fits["cy_flip"] & fits["cz_flip"]))
    return open_.unionByName(narrow.where(ok).select(open_.columns))


_KEEP = ("cid", "head", "pattern", "p1", "d1", "p2", "d2", *CLASSES, "x", "w", "o1", "o2", "fact1", "fact2", "link_fact", *[f"t{n}_{c}" for n in (1, 2) for c in TIME_COLUMNS])


def _one_subject(rules: DataFrame, first: DataFrame, second: DataFrame, once: bool) -> DataFrame:
    """Matches of one-subject rules; `once` leaves one order of pairs whose order doesn't matter."""
    r = small(rules.where("pattern <> 'b'").select("cid", "head", "pattern", "p0", "d0", "p1", "d1", "p2", "d2", *CLASSES))
    out = side(first, 1).join(r, ["p1", "d1"]).join(side(second, 2), ["x", "p2", "d2"]).where("fact1 <> fact2 and o1 <> o2")
    if once:
        out = out.where(~_unordered() | (F.col("fact1") < F.col("fact2")))
    return out.withColumns({"w": F.lit(None).cast("string"), "link_fact": F.lit(None).cast("string")}).select(*_KEEP)


def _two_subjects(kg: KnowledgeGraph, rules: DataFrame, first: DataFrame, second: DataFrame) -> DataFrame:
    r = small(rules.where("pattern = 'b'").select("cid", "head", "pattern", "p0", "d0", "p1", "d1", "p2", "d2", *CLASSES))
    hop = links(kg.facts).select("x", "p0", "d0", F.col("y").alias("w"), "link_fact").where("x <> w")
    hop = hop.join(small(r.select("p0", "d0").distinct()), ["p0", "d0"], "left_semi")
    return side(first, 1).join(r, ["p1", "d1"]).join(hop, ["x", "p0", "d0"]).join(side(second, 2, "w"), ["w", "p2", "d2"]).where("fact1 <> fact2").select(*_KEEP)


def _conflicts(pairs: DataFrame, kg: KnowledgeGraph, shape: _Shape) -> DataFrame:
    out = _restricted(pairs, kg) if shape.narrow else pairs
    return out.withColumn("verdict", _violated(shape)).where("verdict = -1")


def _slots(rules: DataFrame) -> DataFrame:
    one = rules.select(F.col("p1").alias("p"), F.col("d1").alias("d")).union(rules.select("p2", "d2"))
    return small(one.distinct())


def _matches(kg: KnowledgeGraph, rules: DataFrame, shape: _Shape, first: DataFrame, second: DataFrame, once: bool) -> DataFrame:
    parts = [_one_subject(rules, first, second, once)] if shape.one else []
    if shape.linked:
        parts.append(_two_subjects(kg, rules, first, second))
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])


def detect_conflicts(kg: KnowledgeGraph, rules: DataFrame) -> DataFrame:
    """cid, x, fact1, fact2, link_fact, verdict of every violated pair; each unordered pair once."""
    shape = _Shape(rules)
    if not shape.heads:
        return kg.facts.sparkSession.createDataFrame([], "cid string, x string, fact1 string, fact2 string, link_fact string, verdict tinyint")
    e = temporal_edges(kg.facts, reverse=True).join(_slots(rules), ["p", "d"], "left_semi")
    return _conflicts(_matches(kg, rules, shape, e, e, True), kg, shape).select(*CONFLICTS)


def check_new_facts(kg: KnowledgeGraph, new: DataFrame, rules: DataFrame) -> DataFrame:
    """Conflicts between new facts and the graph: a new fact may be the first or the second atom."""
    shape = _Shape(rules)
    if not shape.heads:
        return kg.facts.sparkSession.createDataFrame([], "new_fact string, cid string, x string, fact1 string, fact2 string, link_fact string, verdict tinyint")
    old = temporal_edges(kg.facts, reverse=True).join(_slots(rules), ["p", "d"], "left_semi")
    fresh = temporal_edges(new, reverse=True).join(_slots(rules), ["p", "d"], "left_semi")
    one = _matches(kg, rules, shape, fresh, old, False).withColumn("new_fact", F.col("fact1"))
    two = _matches(kg, rules, shape, old, fresh, False).withColumn("new_fact", F.col("fact2"))
    found = _conflicts_kept(one, kg, shape).unionByName(_conflicts_kept(two, kg, shape))
    # heads that don't mind the order are found from both sides
    swap = F.col("unordered") & (F.col("fact1") > F.col("fact2"))
    low, high = F.when(swap, F.col("fact2")).otherwise(F.col("fact1")), F.when(swap, F.col("fact1")).otherwise(F.col("fact2"))
    return found.withColumns({"fact1": low, "fact2": high}).select("new_fact", *CONFLICTS).distinct()


def _conflicts_kept(pairs: DataFrame, kg: KnowledgeGraph, shape: _Shape) -> DataFrame:
    return _conflicts(pairs, kg, shape).select("new_fact", *CONFLICTS, _unordered().alias("unordered"))


def self_conflicts(facts: DataFrame) -> DataFrame:
    """Facts whose interval surely starts after its end."""
    return facts.where(F.col("is_temporal") & is_inverted(Interval.columns()))


def count_conflicts(conflicts: DataFrame, distinct: bool = True) -> DataFrame:
    pair = F.struct(F.least("fact1", "fact2"), F.greatest("fact1", "fact2"))
    n = F.count_distinct(pair) if distinct else F.count("*")
    return conflicts.agg(n.alias("n_conflicts"))


def conflict_profile(conflicts: DataFrame, rules: DataFrame) -> DataFrame:
    """Conflicts per rule, their share of all, and the rule's rank by them."""
    from pyspark.sql import Window

    per = conflicts.groupBy("cid").agg(F.count("*").alias("n"))
    total = per.agg(F.sum("n").alias("total"))
    named = per.join(rules.select("cid", "head", "p1", "p2"), "cid").join(F.broadcast(total), F.col("n") <= F.col("total"))
    return named.select("cid", "head", "p1", "p2", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"), F.rank().over(Window.orderBy(F.desc("n"))).alias("place"))


def conflict_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """How many distinct pairs both, only the first or only the second detector reports."""
    pair = [F.least("fact1", "fact2").alias("f1"), F.greatest("fact1", "fact2").alias("f2")]
    pa, pb = a.select(*pair).distinct(), b.select(*pair).distinct()
    n = lambda df, name: df.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")
    return n(pa.intersect(pb), "both").union(n(pa.exceptAll(pb), "first")).union(n(pb.exceptAll(pa), "second"))


def _slot(text: str) -> tuple[str, int]:
    return (text[:-3], -1) if text.endswith("^-1") else (text, 1)


def parse_rules(spark: SparkSession, source: str | Path | list[dict]) -> DataFrame:
    """Hand-written rules from JSON: head, slots [first, second], link, classes {x, y, z, w}; a slot may end in ^-1."""
    rules = source if isinstance(source, list) else json.loads(Path(source).read_text())
    rows = []
    for r in rules:
        if r["head"] not in (*PREDICATES, "never"):
            raise ValueError(f"no head {r['head']}")
        (p1, d1), (p2, d2) = _slot(r["slots"][0]), _slot(r["slots"][-1])
        p0, d0 = _slot(r["link"]) if r.get("link") else (None, None)
        pattern = "b" if p0 else ("a_same" if (p1, d1) == (p2, d2) else "a_diff")
        if pattern == "b" and r["head"] in ("disjoint", "never"):
            raise ValueError(f"{r['head']} doesn't fit two subjects")
        c = [r.get("classes", {}).get(v, "*") for v in "xyzw"]
        rows.append((r["id"], r["head"], pattern, p0, d0, p1, d1, p2, d2, *c, None, None, None, None, None, "entity", "hand"))
    schema = "cid string, head string, pattern string, p0 string, d0 tinyint, p1 string, d1 tinyint, p2 string, d2 tinyint, cx string, cy string, cz string, cw string, support long, n_pos long, n_neg long, n_unk long, confidence double, level string, origin string"
    return spark.createDataFrame(rows, schema).select(*CONSTRAINTS)


#: The hand-written rules over the projected graph; H1 is the deliberately coarse one.
HANDWRITTEN = [
    {"id": "H1", "head": "disjoint", "slots": ["in_state", "in_state"]},
    {"id": "H2", "head": "before", "slots": ["said_system", "said_user"]},
    {"id": "H3", "head": "before", "slots": ["said_system", "said_assistant"]},
    {"id": "H4", "head": "never", "slots": ["ordered_on", "ordered_on"]},
    {"id": "H5", "head": "never", "slots": ["placed_order^-1", "placed_order^-1"]},
    {"id": "H6", "head": "include", "slots": ["active_as", "placed_order"]},
    {"id": "H7", "head": "include", "slots": ["active_as", "ordered_on"], "link": "placed_order"},
    {"id": "H8", "head": "include", "slots": ["supplier_active", "supplied_by^-1"]},
    {"id": "H9", "head": "never", "slots": ["active_as", "active_as"]},
    {"id": "H10", "head": "never", "slots": ["supplier_active", "supplier_active"]},
    {"id": "H11", "head": "before", "slots": ["ordered_on", "contains_part"]},
    {"id": "H12", "head": "never", "slots": ["supplied_by", "supplied_by"]},
]
