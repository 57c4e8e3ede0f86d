"""Time values of uneven granularity, possibly absent, and their three-valued comparison.

A granule is a half-open range [lo, hi) of microseconds (or of ordinals) with a
granularity code; an absent time has null bounds. Comparisons give true, false or
null for unknown, and SQL's AND, OR and NOT are then the logic needed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed codes of granularity.
INSTANT, DAY, MONTH, YEAR = 0, 1, 2, 3
UNITS = {"day": DAY, "month": MONTH, "year": YEAR}
DAY_MICROS = 86_400_000_000

TIME_COLUMNS = ("ts_lo", "ts_hi", "ts_gran", "te_lo", "te_hi", "te_gran")


@dataclass(frozen=True)
class Granule:
    lo: Column
    hi: Column
    gran: Column

    def struct(self) -> Column:
        return F.struct(self.lo.alias("lo"), self.hi.alias("hi"), self.gran.alias("gran"))

    @staticmethod
    def of(column: Column) -> Granule:
        return Granule(column["lo"], column["hi"], column["gran"])

    def when(self, condition: Column) -> Granule:
        """This granule where the condition holds, absent elsewhere."""
        return Granule(F.when(condition, self.lo), F.when(condition, self.hi), F.when(condition, self.gran))


@dataclass(frozen=True)
class Interval:
    start: Granule
    end: Granule

    @staticmethod
    def columns(prefix: str = "") -> Interval:
        """The six flat columns of a fact, under a prefix."""
        c = [F.col(f"{prefix}{x}") for x in TIME_COLUMNS]
        return Interval(Granule(*c[:3]), Granule(*c[3:]))

    def named(self) -> list[Column]:
        g = (self.start.lo, self.start.hi, self.start.gran, self.end.lo, self.end.hi, self.end.gran)
        return [c.cast("tinyint" if n.endswith("gran") else "long").alias(n) for c, n in zip(g, TIME_COLUMNS)]

    def struct(self) -> Column:
        return F.struct(self.start.struct().alias("start"), self.end.struct().alias("end"))


def micros(ts: Column) -> Column:
    """Microseconds of a timestamp's wall-clock value, whatever the session's time zone."""
    return F.unix_micros(F.from_utc_timestamp(ts.cast("timestamp"), F.current_timezone()))


def instant(at: Column) -> Granule:
    at = at.cast("long")
    return Granule(at, at + 1, F.when(at.isNotNull(), F.lit(INSTANT)))


ordinal = instant


def missing() -> Granule:
    none = F.lit(None)
    return Granule(none.cast("long"), none.cast("long"), none.cast("tinyint"))


def granule_of(ts: Column, unit: str) -> Granule:
    """The calendar day, month or year that holds a timestamp."""
    first = F.date_trunc(unit, ts.cast("timestamp"))
    lo = micros(first)
    hi = lo + DAY_MICROS if unit == "day" else micros(F.add_months(first, 1 if unit == "month" else 12).cast("timestamp"))
    return Granule(lo, hi, F.when(lo.isNotNull(), F.lit(UNITS[unit])))


def granule(label: Column) -> Granule:
    """A label YYYY, YYYY-MM, YYYY-MM-DD or YYYY-MM-DD hh:mm:ss; any other label is absent."""
    label = F.trim(label)
    year = label.rlike(r"^\d{4}$")
    month = label.rlike(r"^\d{4}-\d{2}$")
    day = label.rlike(r"^\d{4}-\d{2}-\d{2}$")
    second = label.rlike(r"^\d{4}-\d{2}-\d{2}[ T]\d{2}:\d{2}:\d{2}$")
    full = F.when(year, F.concat(label, F.lit("-01-01"))).when(month, F.concat(label, F.lit("-01"))).when(day | second, F.replace(label, F.lit("T"), F.lit(" ")))
    ts = F.try_to_timestamp(F.when(second, full).otherwise(F.concat(full, F.lit(" 00:00:00"))), F.lit("yyyy-MM-dd HH:mm:ss"))
    parts = [(year, granule_of(ts, "year")), (month, granule_of(ts, "month")), (day, granule_of(ts, "day")), (second, instant(micros(ts)))]

    def pick(name: str) -> Column:
        out = F.lit(None)
        for cond, g in parts:
            out = F.when(cond, getattr(g, name)).otherwise(out)
        return out

    return Granule(pick("lo"), pick("hi"), pick("gran"))


def interval_from_qualifiers(q: Column) -> Interval:
    """Interval of a map of qualifiers: point_in_time, or start_time and end_time, each possibly left out."""
    point = granule(F.try_element_at(q, F.lit("point_in_time")))
    start, end = granule(F.try_element_at(q, F.lit("start_time"))), granule(F.try_element_at(q, F.lit("end_time")))
    both = lambda a, b: Granule(F.coalesce(a.lo, b.lo), F.coalesce(a.hi, b.hi), F.coalesce(a.gran, b.gran))
    return Interval(both(start, point), both(end, point))


def lt(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    """a before b: known where the ranges don't meet, or are the same one."""
    same = (a.lo == b.lo) & (a.hi == b.hi)
    if same_granule == "unknown":
        same = same & (a.gran == INSTANT)
    return F.when(a.hi <= b.lo, True).when((b.hi <= a.lo) | same, False)


def eq(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    """a equals b: known where the ranges don't meet, or are the same one."""
    same = (a.lo == b.lo) & (a.hi == b.hi)
    if same_granule == "unknown":
        same = same & (a.gran == INSTANT)
    return F.when(same, True).when((a.hi <= b.lo) | (b.hi <= a.lo), False)


def le(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    return lt(a, b, same_granule) | eq(a, b, same_granule)


def gt(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    return lt(b, a, same_granule)


def ge(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    return le(b, a, same_granule)


def ne(a: Granule, b: Granule, same_granule: str = "equal") -> Column:
    return ~eq(a, b, same_granule)


def interval_ne(i: Interval, j: Interval, same_granule: str = "equal") -> Column:
    return ne(i.start, j.start, same_granule) | ne(i.end, j.end, same_granule)


def is_inverted(i: Interval) -> Column:
    """The interval surely starts after its end."""
    return F.coalesce(gt(i.start, i.end), F.lit(False))
