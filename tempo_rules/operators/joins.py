"""Joins on time that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the last right row of its key at or before it.

    Both sides are stacked and swept once per key: one shuffle, no pairs. Rows of
    equal time take the right row; among right rows of equal time, the greatest values.
    """
    packed = F.struct(*[F.col(v) for v in values])
    l = left.select(F.struct(*left.columns).alias("row"), *[F.col(b) for b in by], F.col(at).alias("at"), F.lit(1).alias("kind"), F.lit(None).cast(right.select(packed.alias("v")).schema["v"].dataType).alias("v"))
    r = right.select(F.lit(None).cast(l.schema["row"].dataType).alias("row"), *[F.col(b) for b in by], F.col(at).alias("at"), F.lit(0).alias("kind"), packed.alias("v"))
    w = Window.partitionBy(*by).orderBy("at", "kind", "v").rowsBetween(Window.unboundedPreceding, 0)
    out = l.unionByName(r).withColumn("last", F.last("v", ignorenulls=True).over(w)).where("kind = 1")
    return out.select("row.*", *[F.col(f"last.{v}").alias(v if v not in left.columns else f"last_{v}") for v in values])


def overlap_join(left: DataFrame, right: DataFrame, by: list[str], lo: str, hi: str, width: int) -> DataFrame:
    """Pairs of rows of a key whose half-open ranges [lo, hi) meet; columns come back as l_* and r_*.

    Ranges are cut into bins of `width`; a pair is reported in its first common bin only.
    """
    def binned(df: DataFrame, side: str) -> DataFrame:
        named = df.select(*[F.col(c).alias(f"{side}_{c}") for c in df.columns])
        first = F.floor(F.col(f"{side}_{lo}") / width).cast("long")
        last = F.floor((F.col(f"{side}_{hi}") - 1) / width).cast("long")
        return named.where(F.col(f"{side}_{lo}") < F.col(f"{side}_{hi}")).withColumn(f"{side}_bin", F.explode(F.sequence(first, last)))

    a, b = binned(left, "l"), binned(right, "r")
    on = a["l_bin"] == b["r_bin"]
    for k in by:
        on = on & (a[f"l_{k}"] == b[f"r_{k}"])
    meet = (F.col(f"l_{lo}") < F.col(f"r_{hi}")) & (F.col(f"r_{lo}") < F.col(f"l_{hi}"))
    first = F.floor(F.greatest(f"l_{lo}", f"r_{lo}") / width).cast("long") == F.col("l_bin")
    return a.join(b, on).where(meet & first).drop("l_bin", "r_bin")


def salted_join(big: DataFrame, other: DataFrame, keys: list[str], salts: int, row: str) -> DataFrame:
    """Inner equi-join where a key may hold much of `big`: big rows are spread, the other side is repeated, every pair comes once."""
    b = big.withColumn("_salt", F.pmod(F.xxhash64(row), F.lit(salts)))
    o = other.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return b.join(o, [*keys, "_salt"]).drop("_salt")


def sessions(events: DataFrame, by: list[str], at: str, gap: int) -> DataFrame:
    """Runs of rows of a key with no more than `gap` between neighbours: keys, lo, hi, n."""
    w = Window.partitionBy(*by).orderBy(at)
    fresh = F.when(F.col(at) - F.lag(at).over(w) <= gap, 0).otherwise(1)
    numbered = events.withColumn("_new", fresh).withColumn("_run", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(*by, "_run").agg(F.min(at).alias("lo"), F.max(at).alias("hi"), F.count("*").alias("n")).drop("_run")
