"""Mixing sources to target weights by entropy balancing.

Rates r of documents, from 0 to a cap, are as near to 1 as they can be (least
relative entropy) under one token constraint for each source: sizes times rates sum
up to the target. The solution tilts exponentially in what the constraint counts:
r = exp(lambda * size), held at the cap, with one lambda for each source. The convex
dual has no closed form; Newton steps solve it, each of which sums gradient and
curvature over a table of how many documents of a source have a size. Rates become
whole copies by rounding that keeps each source's words near its target.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import broadcast_if_small, materialize, release

WEIGHTS = (1, 2, 3)
MAX_COPIES = 3
#: Share of its target by which a source's expected words may miss it; most Newton steps (a bracket halves where one leaves it).
CLOSE, STEPS = 1e-7, 100
#: Offsets and seeds tried when rates are rounded; rows rounded in one go.
OFFSETS, SEEDS, CHUNK_ROWS = 16, 64, 4096


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, cap: float = MAX_COPIES) -> DataFrame:
    """Add `target` to rows of (source, source_size): all words shared by weight; no source above cap times its size, the excess reshared.

    Sources weigh in order of code points, null last. A source is full when its size
    is small for its weight, so one level decides; it rises until no other is above.
    """
    place = F.row_number().over(Window.orderBy(F.asc_nulls_last("source")))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(place - 1, F.lit(len(weights))) + 1).cast("int"))
    table = materialize(sizes.withColumn("weight", weight), "weights")
    full = lambda level: F.col("weight") * F.lit(level) > F.lit(cap) * F.col("source_size")
    total = table.agg(F.sum("source_size")).first()[0] or 0
    level, before = 0.0, None
    while True:
        held, by, n = table.agg(F.sum(F.when(full(level), F.col("source_size"))), F.sum(F.when(~full(level), F.col("weight"))), F.count(F.when(full(level), 1))).first()
        if n == before or not by:
            break
        level, before = (total - cap * (held or 0)) / by, n
    return table.withColumn("target", F.when(full(level), F.lit(float(cap)) * F.col("source_size")).otherwise(F.col("weight") * F.lit(level))).drop("weight")


def _rate(size: Column, tilt: Column, mean: Column, cap: float) -> Column:
    """exp(tilt * size / mean size) up to the cap."""
    return F.least(F.lit(float(cap)), F.exp(F.least(tilt * size / mean, F.lit(50.0))))


def _exact(value: Column) -> Column:
    """A sum that doesn't depend on the order of its terms."""
    return F.sum(value.cast("decimal(28,6)")).cast("double")


def solve(cells: DataFrame, goals: DataFrame, cap: float = MAX_COPIES) -> DataFrame:
    """Tilts of sources: rows of `goals` (source, source_size, n, target, ..) with tilt and mean, from cells (source, size, n) of sizes above 0.

    A tilt is the root of the dual's gradient, which ascends in it. It's null where no
    inner solution exists: targets of 0 (rate 0) and of cap times the size (rate cap).
    """
    inner = (F.col("target") > 0) & (F.col("target") < F.lit(float(cap)) * F.col("source_size") * (1 - CLOSE)) & (F.col("source_size") > 0)
    goals = goals.withColumn("mean", F.col("source_size") / F.greatest("n", F.lit(1)))
    state = goals.where(inner).select(F.col("source").alias("s"), "target", "mean", F.lit(0.0).alias("tilt"), F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"), F.lit(None).cast("double").alias("miss"))
    many = goals.count()
    small = lambda t: broadcast_if_small(t, many)
    state = materialize(state, "dual")
    for _ in range(STEPS):
        at = cells.join(small(state), cells.source.eqNullSafe(state.s))
        rate = _rate(F.col("size"), F.col("tilt"), F.col("mean"), cap)
        x = F.col("size") / F.col("mean")
        words, bend = F.col("n") * F.col("size") * rate, F.when(rate < cap, F.col("n") * F.col("size") * x * rate).otherwise(0.0)
        sums = at.groupBy(F.col("source").alias("g")).agg(_exact(words).alias("words"), _exact(bend).alias("bend"))
        both = state.join(small(sums), state.s.eqNullSafe(sums.g))
        over = F.col("words") - F.col("target")
        lo, hi = F.when(over < 0, F.col("tilt")).otherwise(F.col("lo")), F.when(over >= 0, F.col("tilt")).otherwise(F.col("hi"))
        step = F.col("tilt") - F.when(F.col("bend") > 0, over / F.col("bend"))
        # where a side of the bracket is open, a step doesn't go far
        near = F.least(F.greatest(step, F.coalesce(lo, F.col("tilt") - 4)), F.coalesce(hi, F.col("tilt") + 4))
        inside = F.coalesce(step.isNotNull() & ((lo.isNull() | (near > lo)) & (hi.isNull() | (near < hi))), F.lit(False))
        new = F.when(inside, near).when(lo.isNotNull() & hi.isNotNull(), (lo + hi) / 2).otherwise(F.col("tilt") + F.when(over < 0, 1.0).otherwise(-1.0) * F.greatest(F.abs("tilt"), F.lit(1.0)))
        miss = F.abs(over) / F.col("target")
        was = state
        state = materialize(both.select("s", "target", "mean", F.when(miss <= CLOSE, F.col("tilt")).otherwise(new).alias("tilt"), lo.alias("lo"), hi.alias("hi"), miss.alias("miss")), "dual")
        worst = state.agg(F.max("miss")).first()[0]
        release(was)
        if worst is None or worst <= CLOSE:
            break
    tilts = state.select("s", "tilt")
    return goals.join(small(tilts), goals.source.eqNullSafe(tilts.s), "left").drop("s")


def mix_documents(docs: DataFrame, weights=WEIGHTS, cap: int = MAX_COPIES) -> DataFrame:
    """doc_id, h (a hash of doc_id and text), size, source_size, target, rate, copies, taken of every document.

    Null source is a source of its own (weighed last); null or empty text has size
    0 and is never taken. The same input gives the same copies, however partitioned.
    Rows that repeat a document each get their copies. Texts of any length are counted
    whole; extra columns, whatever their names, are ignored; an empty input gives an
    empty result. Under a target below a source's size, long documents leave first.
    """
    slim = docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), F.xxhash64("doc_id", "text").alias("h"))
    slim = materialize(slim, "sizes")
    cells = materialize(slim.groupBy("source", "size").agg(F.count("*").alias("n")), "cells")
    solid = F.col("size") > 0
    sizes = cells.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"), F.coalesce(F.sum(F.when(solid, F.col("n"))), F.lit(0)).alias("n"), F.sum("n").alias("n_all"))
    goals = solve(cells.where(solid), targets(sizes, weights, cap), cap)
    goals = materialize(goals.select(F.col("source").alias("s"), "source_size", "target", "tilt", "mean", F.ceil(F.col("n_all") / CHUNK_ROWS).alias("chunks")), "goals")
    rated = slim.join(broadcast_if_small(goals), slim.source.eqNullSafe(goals.s)).drop("s")
    edge = F.when((F.col("target") > 0) & (F.col("size") > 0), F.lit(float(cap))).otherwise(0.0)
    rate = F.when(F.col("tilt").isNull() | (F.col("size") == 0), edge).otherwise(_rate(F.col("size"), F.col("tilt"), F.col("mean"), cap))
    rated = rated.withColumn("rate", rate).withColumn("chunk", F.pmod("h", "chunks")).drop("tilt", "mean", "chunks")
    # in each chunk, sizes descend: a whole copy more or less then costs little
    along = Window.partitionBy("source", "chunk").orderBy(F.desc("size"), "h", "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    ranked = materialize(rated.withColumn("upto", F.sum(F.col("rate")).over(along)), "ranked")
    # each try rounds every rate up or down; the one that meets the words best is kept.
    # Systematic tries suit many documents, independent ones suit few large ones.
    systematic = lambda u: F.floor(F.col("upto") + u) - F.floor(F.col("upto") - F.col("rate") + u)
    independent = lambda seed: F.floor(F.col("rate") + F.pmod(F.xxhash64("h", seed), F.lit(1 << 30)) / F.lit(float(1 << 30)))
    held = lambda c: F.when(F.col("size") > 0, F.least(F.greatest(c.cast("long"), F.lit(0)), F.lit(cap))).otherwise(0).cast("long")
    tries = [held(systematic(F.lit((i + 0.5) / OFFSETS))) for i in range(OFFSETS)] + [held(independent(F.lit(i))) for i in range(SEEDS)]
    names = [f"e{i}" for i in range(len(tries))]
    wanted = F.sum((F.col("rate") * F.col("size")).cast("decimal(28,6)"))
    error = [F.abs(F.sum(c * F.col("size")).cast("decimal(28,6)") - wanted).alias(e) for c, e in zip(tries, names)]
    best = ranked.groupBy("source", "chunk").agg(*error)
    found = F.array_position(F.array(*names), F.array_min(F.array(*names))) - 1
    best = best.select(F.col("source").alias("bs"), F.col("chunk").alias("bc"), found.cast("int").alias("best"))
    out = ranked.join(best, ranked.source.eqNullSafe(best.bs) & (ranked.chunk == best.bc))
    chosen = F.when(F.col("best") < OFFSETS, held(systematic((F.col("best") + 0.5) / OFFSETS))).otherwise(held(independent(F.col("best") - OFFSETS)))
    out = out.withColumn("copies", chosen)
    return out.select("doc_id", "h", "size", "source_size", "target", "rate", "copies", (F.col("copies") * F.col("size")).alias("taken"))
