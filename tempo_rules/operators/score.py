"""Support and confidence of rules, per pair of facts or per subject.

All heads are evaluated in one pass over the pairs. A subject's verdict is the least
of its pairs' verdicts: one negative pair makes it negative, else an unknown one
makes it unknown. Sums per slots and subject come first, then sums per rule.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.granule import Granule, Interval
from ..functions.predicates import PREDICATES
from .match import time_of

RULE = ("head", "pattern", "p0", "d0", "p1", "d1", "p2", "d2")
#: Bit of each rule head in an alive-mask; ordered heads have a bit for either order.
BITS = {"start": 0, "finish": 1, "disjoint": 2, "before_12": 3, "before_21": 4, "include_12": 5, "include_21": 6}
ALL = (1 << len(BITS)) - 1


def ratio(pos: Column, neg: Column) -> Column:
    return F.try_divide(pos.cast("double"), (pos + neg).cast("double"))


def fact_scores(verdicts: DataFrame, by: list[str] | tuple[str, ...] = ()) -> DataFrame:
    """n_pos, n_neg, n_unk, support and confidence of rows with a verdict, per group."""
    return with_scores(verdicts.groupBy(*by).agg(*[F.count_if(F.col("verdict") == v).alias(n) for n, v in (("n_pos", 1), ("n_neg", -1), ("n_unk", 0))]))


def with_scores(counts: DataFrame) -> DataFrame:
    return counts.withColumns({"support": F.col("n_pos"), "confidence": ratio(F.col("n_pos"), F.col("n_neg"))})


def entity_verdicts(verdicts: DataFrame, by: list[str] | tuple[str, ...] = ()) -> DataFrame:
    """One verdict for each subject and group: the least of its pairs' verdicts."""
    return verdicts.groupBy(*by, "x").agg(F.min("verdict").alias("verdict"))


def entity_scores(verdicts: DataFrame, by: list[str] | tuple[str, ...] = ()) -> DataFrame:
    return fact_scores(entity_verdicts(verdicts, by), by)


def _pair_columns(mask: Column | None) -> dict[str, Column]:
    one, two = time_of(1), time_of(2)
    same = (F.col("p1") == F.col("p2")) & (F.col("d1") == F.col("d2"))
    raw = {
        "start": PREDICATES["start"](one, two), "finish": PREDICATES["finish"](one, two), "disjoint": F.when(same, PREDICATES["disjoint"](one, two)),
        "before_12": PREDICATES["before"](one, two), "before_21": PREDICATES["before"](two, one), "include_12": PREDICATES["include"](one, two), "include_21": PREDICATES["include"](two, one),
    }
    if mask is None:
        return raw
    return {k: F.when(F.getbit(mask, F.lit(BITS[k])) == 1, v) for k, v in raw.items()}


def _sums(level: str, cols: dict[str, Column]) -> list[Column]:
    if level == "entity":
        return [F.min(v).alias(k) for k, v in cols.items()]
    return [F.struct(*[F.count_if(v == w).alias(n) for n, w in (("n_pos", 1), ("n_neg", -1), ("n_unk", 0))]).alias(k) for k, v in cols.items()]


def _unpivot(per: DataFrame, heads: list[str], key: list[str]) -> DataFrame:
    items = [F.struct(F.lit(h).alias("h"), F.col(h).alias("v")) for h in heads]
    return per.select(*key, F.explode(F.array(*items)).alias("e")).select(*key, "e.h", "e.v").where("v is not null")


def _rules(rows: DataFrame) -> DataFrame:
    """Rows of slots 1 and 2 and a head with its order, as rules whose first slot is the head's first argument."""
    back = F.col("h").endswith("_21")
    pick = lambda a, b: F.when(back, F.col(b)).otherwise(F.col(a))
    return rows.withColumns({"q1": pick("p1", "p2"), "e1": pick("d1", "d2"), "q2": pick("p2", "p1"), "e2": pick("d2", "d1")}).drop("p1", "d1", "p2", "d2").withColumnsRenamed({"q1": "p1", "e1": "d1", "q2": "p2", "e2": "d2"}).withColumn("head", F.substring_index("h", "_", 1))


def _counted(level: str, rows: DataFrame, key: list[str]) -> DataFrame:
    if level == "entity":
        return rows.groupBy(*key).agg(*[F.count_if(F.col("v") == w).alias(n) for n, w in (("n_pos", 1), ("n_neg", -1), ("n_unk", 0))])
    return rows.groupBy(*key).agg(*[F.sum(f"v.{n}").alias(n) for n in ("n_pos", "n_neg", "n_unk")])


def score_one_subject(matches: DataFrame, level: str = "entity", mask: Column | None = None, classes: tuple[str, ...] = ()) -> DataFrame:
    """Counts of all rules over pairs of one subject: head, pattern, slots, [classes], n_pos, n_neg, n_unk.

    For one slot both orders of `before` and `include` belong to the same rule.
    """
    key = ["p1", "d1", "p2", "d2", *classes]
    cols = _pair_columns(mask)
    per = matches.groupBy("x", *key).agg(*_sums(level, cols)) if level == "entity" else matches.groupBy(*key).agg(*_sums(level, cols))
    if level == "entity":
        same = (F.col("p1") == F.col("p2")) & (F.col("d1") == F.col("d2"))
        for h in ("before", "include"):
            both = F.when(same, F.least(f"{h}_12", f"{h}_21"))
            per = per.withColumn(f"{h}_12", F.coalesce(both, F.col(f"{h}_12"))).withColumn(f"{h}_21", F.when(~same, F.col(f"{h}_21")))
    rows = _rules(_unpivot(per, list(cols), key))
    rule = ["head", "p1", "d1", "p2", "d2", *classes]
    out = _counted(level, rows, rule).where("n_pos + n_neg + n_unk > 0")
    pattern = F.when((F.col("p1") == F.col("p2")) & (F.col("d1") == F.col("d2")), "a_same").otherwise("a_diff")
    none = {"p0": F.lit(None).cast("string"), "d0": F.lit(None).cast("tinyint")}
    return out.withColumn("pattern", pattern).withColumns(none).select(*RULE, *classes, "n_pos", "n_neg", "n_unk")


#: What two single ticks are to each other, as bits: earlier, equal, later.
TICKS = (1, 2, 4)


def is_tick() -> Column:
    """Facts at one instant: all verdicts over two of them follow from which is earlier."""
    c = F.col
    return F.coalesce((c("ts_hi") == c("ts_lo") + 1) & (c("te_lo") == c("ts_lo")) & (c("te_hi") == c("ts_hi")), F.lit(False))


def tick_order(a: Column, b: Column) -> Column:
    return F.when(a < b, TICKS[0]).when(a == b, TICKS[1]).otherwise(TICKS[2])


def tick_verdict(head: str, swapped: bool = False) -> list[Column]:
    """The verdict of a head for each of TICKS, by the head's own predicate."""
    def at(t: int) -> Interval:
        g = Granule(F.lit(t).cast("long"), F.lit(t + 1).cast("long"), F.lit(0).cast("tinyint"))
        return Interval(g, g)

    pairs = [(at(0), at(1)), (at(0), at(0)), (at(1), at(0))]
    return [PREDICATES[head](*(reversed(x) if swapped else x)) for x in pairs]


def score_ticks(edges: DataFrame) -> DataFrame:
    """score_one_subject at entity level over edges of single ticks, which lie by subject: no pair leaves its task.

    A subject's pairs of two slots leave one set of TICKS; subjects with the same sets are counted before verdicts are taken.
    """
    a = edges.select("x", *[F.col(c).alias(f"{n}1") for c, n in (("p", "p"), ("d", "d"), ("y", "o"), ("fact", "fact"), ("ts_lo", "at"))])
    b = a.select("x", *[F.col(f"{c}1").alias(f"{c}2") for c in ("p", "d", "o", "fact", "at")])
    same = (F.col("p1") == F.col("p2")) & (F.col("d1") == F.col("d2"))
    pairs = a.join(b, "x").where("o1 <> o2 and fact1 <> fact2 and (p1 < p2 or (p1 = p2 and (d1 < d2 or (d1 = d2 and fact1 < fact2))))")
    key = ["p1", "d1", "p2", "d2"]
    per = pairs.groupBy("x", *key).agg(F.bit_or(tick_order(F.col("at1"), F.col("at2"))).alias("ticks"))
    sets = per.groupBy(*key, "ticks").agg(F.count("*").alias("n"))
    least = lambda h, swapped=False: F.least(*[F.when(F.col("ticks").bitwiseAND(bit) != 0, v) for bit, v in zip(TICKS, tick_verdict(h, swapped))])
    one = {"start": least("start"), "finish": least("finish"), "disjoint": F.when(same, least("disjoint"))}
    for h in ("before", "include"):
        one |= {f"{h}_12": F.when(same, F.least(least(h), least(h, True))).otherwise(least(h)), f"{h}_21": F.when(~same, least(h, True))}
    rows = _rules(_unpivot(sets.withColumns(one), list(one), [*key, "n"]))
    rule = ["head", "p1", "d1", "p2", "d2"]
    counts = [F.sum(F.when(F.col("v") == w, F.col("n")).otherwise(0)).alias(c) for c, w in (("n_pos", 1), ("n_neg", -1), ("n_unk", 0))]
    pattern = F.when(same, "a_same").otherwise("a_diff")
    none = {"p0": F.lit(None).cast("string"), "d0": F.lit(None).cast("tinyint")}
    return rows.groupBy(*rule).agg(*counts).withColumn("pattern", pattern).withColumns(none).select(*RULE, "n_pos", "n_neg", "n_unk")


def linked_bit(head: str) -> int:
    """The bit of a head in the masks of linked subjects."""
    return BITS.get(head, BITS.get(f"{head}_12", -1))


def score_linked_subjects(matches: DataFrame, level: str = "entity", classes: tuple[str, ...] = (), mask: Column | None = None) -> DataFrame:
    """The same for two linked subjects; the subject counted is the first one. Heads whose bit isn't in the mask aren't evaluated."""
    key = ["p0", "d0", "p1", "d1", "p2", "d2", *classes]
    cols = {h: v for h, v in (("start", "start"), ("finish", "finish"), ("before", "before"), ("include", "include"))}
    cols = {h: PREDICATES[h](time_of(1), time_of(2)) for h in cols}
    if mask is not None:
        cols = {h: F.when(F.getbit(mask, F.lit(linked_bit(h))) == 1, v) for h, v in cols.items()}
    per = matches.groupBy(*(["x"] if level == "entity" else []), *key).agg(*_sums(level, cols))
    rows = _unpivot(per, list(cols), key).withColumnRenamed("h", "head")
    out = _counted(level, rows, ["head", *key]).where("n_pos + n_neg + n_unk > 0")
    return out.withColumn("pattern", F.lit("b")).select(*RULE, *classes, "n_pos", "n_neg", "n_unk")


def exclusion_scores(edges: DataFrame, level: str = "entity") -> DataFrame:
    """`never`: a subject has one object of a slot. Positive: exactly one; negative: more (or, per pair, each pair of two)."""
    per = edges.groupBy("x", "p", "d", "y").agg(F.count("*").alias("k")).groupBy("x", "p", "d").agg(F.count("*").alias("n"), F.sum("k").alias("all"), F.sum(F.col("k") * F.col("k")).alias("sq"))
    pos = F.count_if(F.col("n") == 1)
    neg = F.count_if(F.col("n") > 1) if level == "entity" else F.sum(F.expr("(all * all - sq) div 2"))
    out = per.groupBy("p", "d").agg(pos.alias("n_pos"), neg.cast("long").alias("n_neg"), F.lit(0).cast("long").alias("n_unk"))
    return out.select(F.lit("never").alias("head"), F.lit("a_same").alias("pattern"), F.lit(None).cast("string").alias("p0"), F.lit(None).cast("tinyint").alias("d0"), F.col("p").alias("p1"), F.col("d").alias("d1"), F.col("p").alias("p2"), F.col("d").alias("d2"), "n_pos", "n_neg", "n_unk")


def matching_cost(edges: DataFrame, pattern: str = "a", link_edges: DataFrame | None = None, heads: int = 6) -> DataFrame:
    """Pairs that matching visits (ordered) and, times the heads, predicates evaluated, from degrees alone."""
    deg = edges.groupBy("x").agg(F.count("*").cast("decimal(38,0)").alias("n"))
    if pattern == "a":
        cost = deg.agg(F.sum(F.expr("cast(n * (n - 1) as decimal(38,0))")).alias("pairs"))
    else:
        w = deg.select(F.col("x").alias("y"), F.col("n").alias("m"))
        cost = deg.join(link_edges, "x").join(w, "y").agg(F.sum(F.expr("cast(n * m as decimal(38,0))")).alias("pairs"))
    return cost.withColumn("evaluations", F.expr(f"cast(pairs * {heads} as decimal(38,0))"))
