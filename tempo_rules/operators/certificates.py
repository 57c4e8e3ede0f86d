"""Subjects' verdicts from the bounds of their facts, without forming pairs.

An envelope holds least and greatest bounds of a subject's facts of one slot. For two
different slots without absent or inverted times and without a shared object, it often
proves the verdict; only subjects that it leaves open need explicit pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.granule import Interval, is_inverted
from .match import side, with_verdict

_BOUNDS = ("ts_lo", "ts_hi", "te_lo", "te_hi")


def envelopes(edges: DataFrame) -> DataFrame:
    """x, p, d, n, least and greatest bounds, whether any fact is absent in a bound or inverted, and a few objects."""
    sums = [f(c).alias(f"{n}_{c}") for c in _BOUNDS for n, f in (("min", F.min), ("max", F.max))]
    odd = F.max((F.col("ts_lo").isNull() | F.col("te_lo").isNull() | is_inverted(Interval.columns())).cast("int"))
    return edges.groupBy("x", "p", "d").agg(F.count("*").alias("n"), odd.alias("odd"), F.min("y").alias("y_min"), F.max("y").alias("y_max"), *sums)


def _proof(head: str) -> tuple[Column, Column]:
    """All pairs positive; some pair negative."""
    c = F.col
    one, two = "a", "b"
    col = lambda s, f, b: c(f"{s}_{f}_{b}")
    if head == "before":
        return col(one, "max", "te_hi") <= col(two, "min", "ts_lo"), col(one, "max", "te_lo") >= col(two, "min", "ts_hi")
    if head == "include":
        return (
            (col(one, "max", "ts_hi") <= col(two, "min", "ts_lo")) & (col(two, "max", "te_hi") <= col(one, "min", "te_lo")),
            (col(two, "min", "ts_hi") <= col(one, "max", "ts_lo")) | (col(one, "min", "te_hi") <= col(two, "max", "te_lo")),
        )
    b = "ts" if head == "start" else "te"
    same = (col(one, "min", f"{b}_lo") == col(two, "max", f"{b}_lo")) & (col(one, "max", f"{b}_lo") == col(two, "min", f"{b}_lo")) & (col(one, "min", f"{b}_hi") == col(two, "max", f"{b}_hi")) & (col(one, "max", f"{b}_hi") == col(two, "min", f"{b}_hi"))
    apart = (col(one, "max", f"{b}_lo") >= col(two, "min", f"{b}_hi")) | (col(two, "max", f"{b}_lo") >= col(one, "min", f"{b}_hi"))
    return same, apart


def entity_verdicts(edges: DataFrame, head: str) -> DataFrame:
    """p1, d1, p2, d2, x, verdict of `head` (start, finish, before or include) over all ordered pairs of different slots."""
    env = envelopes(edges)
    names = [c for c in env.columns if c not in ("x",)]
    a = env.select("x", *[F.col(c).alias(f"a_{c}") for c in names])
    b = env.select("x", *[F.col(c).alias(f"b_{c}") for c in names])
    both = a.join(b, "x").where("not (a_p = b_p and a_d = b_d)")
    # objects can't be shared when the ranges of their names don't meet
    plain = (F.col("a_odd") == 0) & (F.col("b_odd") == 0) & ((F.col("a_y_max") < F.col("b_y_min")) | (F.col("b_y_max") < F.col("a_y_min")))
    positive, negative = _proof(head)
    judged = both.withColumn("verdict", F.when(plain & positive, 1).when(plain & negative, -1).cast("tinyint"))
    key = [F.col("a_p").alias("p1"), F.col("a_d").alias("d1"), F.col("b_p").alias("p2"), F.col("b_d").alias("d2"), "x"]
    proved = judged.where("verdict is not null").select(*key, "verdict")
    left = judged.where("verdict is null").select(*key)
    # facts of the slots left open meet, and no others
    pairs = side(edges, 1).join(left, ["x", "p1", "d1"]).join(side(edges, 2), ["x", "p2", "d2"]).where("fact1 <> fact2 and o1 <> o2")
    pairs = with_verdict(pairs, head)
    return proved.unionByName(pairs.groupBy("p1", "d1", "p2", "d2", "x").agg(F.min("verdict").alias("verdict")))


def hubs(edges: DataFrame, limit: int) -> DataFrame:
    """Subjects with more facts of a slot than limit: reported, so that no run skips them silently."""
    return edges.groupBy("x", "p", "d").agg(F.count("*").alias("n")).where(F.col("n") > limit)
