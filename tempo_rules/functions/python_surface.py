"""Python functions beside the core path: odd date labels, a brute-force checker, agreement, rule atoms."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

_MONTHS = {m: i + 1 for i, m in enumerate(("jan", "feb", "mar", "apr", "may", "jun", "jul", "aug", "sep", "oct", "nov", "dec"))}


@pandas_udf(T.StringType())
def granule_label(label: pd.Series) -> pd.Series:
    """Labels such as 'July 2003', '12 May 1999' or '1990s?' as YYYY[-MM[-DD]]; others are null."""
    import re

    def one(x: str | None) -> str | None:
        words = re.findall(r"[A-Za-z]+|\d+", x or "")
        year = next((w for w in words if len(w) == 4 and w.isdigit()), None)
        month = next((_MONTHS[w[:3].lower()] for w in words if w[:3].lower() in _MONTHS), None)
        day = next((int(w) for w in words if w.isdigit() and len(w) <= 2 and 1 <= int(w) <= 31), None)
        if year is None:
            return None
        return year if month is None else f"{year}-{month:02d}" if day is None else f"{year}-{month:02d}-{day:02d}"

    return label.map(one)


def brute_force_before(edges: DataFrame, p1: str, p2: str) -> DataFrame:
    """x, verdict of before(p1, p2) by plain loops over each subject's instant facts: a check for small data."""

    def check(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        verdicts = []
        for a in rows[rows.p == p1].itertuples():
            for b in rows[rows.p == p2].itertuples():
                if a.fact_id != b.fact_id and a.y != b.y:
                    verdicts.append(1 if a.te_lo < b.ts_lo else -1 if a.te_lo > b.ts_lo else 0)
        return pd.DataFrame({"x": [key[0]], "verdict": [min(verdicts)]}) if verdicts else pd.DataFrame({"x": [], "verdict": []})

    used = edges.where(F.col("p").isin(p1, p2) & (F.col("d") == 1)).select("x", "y", "p", "fact_id", "ts_lo", "te_lo")
    return used.groupBy("x").applyInPandas(check, "x string, verdict int")


@pandas_udf(T.DoubleType())
def item_agreement(grade: pd.Series) -> float:
    """Share of agreeing pairs of raters of one item: a grouped aggregate."""
    n = len(grade)
    return float(((grade.value_counts() ** 2).sum() - n) / (n * (n - 1))) if n > 1 else None


def kappa_by_aggregate(ratings: DataFrame) -> DataFrame:
    """Fleiss' kappa from the grouped aggregate and grade shares, as a cross-check of the built-in form."""
    observed = ratings.groupBy("item").agg(item_agreement("grade").alias("a")).agg(F.avg("a").alias("observed"))
    total = ratings.count()
    chance = ratings.groupBy("grade").agg((F.count("*") / total).alias("share")).agg(F.sum(F.col("share") * F.col("share")).alias("chance"))
    return observed.join(F.broadcast(chance), F.lit(True)).select(F.round(F.try_divide(F.col("observed") - F.col("chance"), 1 - F.col("chance")), 6).alias("kappa"))


@udtf(returnType=T.StructType([T.StructField("atom", T.IntegerType()), T.StructField("property", T.StringType()), T.StructField("direction", T.IntegerType()), T.StructField("subject", T.StringType()), T.StructField("object", T.StringType())]))
class FactAtoms:
    """The body atoms of a hand-written rule (JSON) as rows."""

    def eval(self, rule: str) -> Iterator[tuple]:
        r = json.loads(rule)
        slot = lambda t: (t[:-3], -1) if t.endswith("^-1") else (t, 1)
        (p1, d1), (p2, d2) = slot(r["slots"][0]), slot(r["slots"][-1])
        yield 1, p1, d1, "x", "y"
        if r.get("link"):
            p0, d0 = slot(r["link"])
            yield 2, p0, d0, "x", "w"
            yield 3, p2, d2, "w", "z"
        else:
            yield 2, p2, d2, "x", "z"
