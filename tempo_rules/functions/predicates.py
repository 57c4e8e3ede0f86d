"""Head predicates over intervals of uncertain bounds.

Each verdict is 1, -1 or 0 (unknown): the positive condition is asked first, then the
negative one. A bound may be absent, so conditions that look redundant aren't: one
known bound can refute a predicate by itself.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .granule import Interval, eq, ge, gt, interval_ne, le, lt, ne

HEADS = ("start", "finish", "before", "disjoint", "include")
SYMMETRIC = ("start", "finish", "disjoint")


def _verdict(positive: Column, negative: Column) -> Column:
    return F.when(positive, F.lit(1)).when(negative, F.lit(-1)).otherwise(F.lit(0)).cast("tinyint")


def _apart(i: Interval, j: Interval, s: str) -> Column:
    return gt(i.start, j.end, s) | lt(i.end, j.start, s)


def start(i: Interval, j: Interval, s: str = "equal") -> Column:
    """The intervals start together."""
    return _verdict(eq(i.start, j.start, s), ne(i.start, j.start, s) | _apart(i, j, s))


def finish(i: Interval, j: Interval, s: str = "equal") -> Column:
    """The intervals end together."""
    return _verdict(eq(i.end, j.end, s), ne(i.end, j.end, s) | _apart(i, j, s))


def _precedes(i: Interval, j: Interval, s: str) -> Column:
    return lt(i.end, j.start, s) | (eq(i.end, j.start, s) & interval_ne(i, j, s))


def before(i: Interval, j: Interval, s: str = "equal") -> Column:
    """i is over when j starts; they may touch unless they are the same."""
    late = gt(i.end, j.start, s) | gt(i.end, j.end, s) | gt(i.start, j.start, s) | gt(i.start, j.end, s)
    return _verdict(_precedes(i, j, s), late)


def disjoint(i: Interval, j: Interval, s: str = "equal") -> Column:
    """One is over when the other starts."""
    over = gt(i.end, j.start, s) & (le(i.end, j.end, s) | le(i.start, j.start, s))
    under = lt(i.start, j.end, s) & (ge(i.end, j.end, s) | ge(i.start, j.start, s))
    return _verdict(_precedes(i, j, s) | _precedes(j, i, s), over | under)


def include(i: Interval, j: Interval, s: str = "equal") -> Column:
    """i covers j."""
    out = gt(i.start, j.start, s) | gt(i.start, j.end, s) | lt(i.end, j.end, s) | lt(i.end, j.start, s)
    return _verdict(le(i.start, j.start, s) & le(j.end, i.end, s), out)


def within(i: Interval, j: Interval, amount: int) -> Column:
    """j starts at most so many microseconds (or ordinals) after i ends: bounds on the gap, three-valued."""
    least, most = j.start.lo - (i.end.hi - 1), j.start.hi - 1 - i.end.lo
    return _verdict((least >= 0) & (most <= amount), (least > amount) | (most < 0))


PREDICATES = {"start": start, "finish": finish, "before": before, "disjoint": disjoint, "include": include}


def verdicts(i: Interval, j: Interval, mask: Column | None = None, same_granule: str = "equal") -> Column:
    """All heads at once as a struct; a head whose bit of the mask is off gives null and isn't evaluated."""
    out = []
    for k, h in enumerate(HEADS):
        v = PREDICATES[h](i, j, same_granule)
        out.append((v if mask is None else F.when(F.getbit(mask, F.lit(k)) == 1, v)).alias(h))
    return F.struct(*out)
