"""SQL functions t_start .. t_include over interval structs, and views of a graph."""

from __future__ import annotations

from pyspark.sql import SparkSession

GRANULE = "STRUCT<lo: BIGINT, hi: BIGINT, gran: TINYINT>"
INTERVAL = f"STRUCT<start: {GRANULE}, end: {GRANULE}>"


def install(spark: SparkSession) -> list[str]:
    """Temporary functions that the analyzer inlines; no Python runs in them."""
    g = GRANULE
    defs = {
        f"g_lt(a {g}, b {g}) RETURNS BOOLEAN": "CASE WHEN a.hi <= b.lo THEN true WHEN b.hi <= a.lo OR (a.lo = b.lo AND a.hi = b.hi) THEN false END",
        f"g_eq(a {g}, b {g}) RETURNS BOOLEAN": "CASE WHEN a.lo = b.lo AND a.hi = b.hi THEN true WHEN a.hi <= b.lo OR b.hi <= a.lo THEN false END",
        f"t_precedes(i {INTERVAL}, j {INTERVAL}) RETURNS BOOLEAN": "g_lt(i.end, j.start) OR (g_eq(i.end, j.start) AND NOT (g_eq(i.start, j.start) AND g_eq(i.end, j.end)))",
        f"t_apart(i {INTERVAL}, j {INTERVAL}) RETURNS BOOLEAN": "g_lt(j.end, i.start) OR g_lt(i.end, j.start)",
        f"t_start(i {INTERVAL}, j {INTERVAL}) RETURNS TINYINT": "CASE WHEN g_eq(i.start, j.start) THEN 1Y WHEN NOT g_eq(i.start, j.start) OR t_apart(i, j) THEN -1Y ELSE 0Y END",
        f"t_finish(i {INTERVAL}, j {INTERVAL}) RETURNS TINYINT": "CASE WHEN g_eq(i.end, j.end) THEN 1Y WHEN NOT g_eq(i.end, j.end) OR t_apart(i, j) THEN -1Y ELSE 0Y END",
        f"t_before(i {INTERVAL}, j {INTERVAL}) RETURNS TINYINT": "CASE WHEN t_precedes(i, j) THEN 1Y WHEN g_lt(j.start, i.end) OR g_lt(j.end, i.end) OR g_lt(j.start, i.start) OR g_lt(j.end, i.start) THEN -1Y ELSE 0Y END",
        f"t_disjoint(i {INTERVAL}, j {INTERVAL}) RETURNS TINYINT": "CASE WHEN t_precedes(i, j) OR t_precedes(j, i) THEN 1Y WHEN (g_lt(j.start, i.end) AND (g_lt(i.end, j.end) OR g_eq(i.end, j.end) OR g_lt(i.start, j.start) OR g_eq(i.start, j.start))) OR (g_lt(i.start, j.end) AND (g_lt(j.end, i.end) OR g_eq(i.end, j.end) OR g_lt(j.start, i.start) OR g_eq(i.start, j.start))) THEN -1Y ELSE 0Y END",
        f"t_include(i {INTERVAL}, j {INTERVAL}) RETURNS TINYINT": "CASE WHEN (g_lt(i.start, j.start) OR g_eq(i.start, j.start)) AND (g_lt(j.end, i.end) OR g_eq(i.end, j.end)) THEN 1Y WHEN g_lt(j.start, i.start) OR g_lt(j.end, i.start) OR g_lt(i.end, j.end) OR g_lt(i.end, j.start) THEN -1Y ELSE 0Y END",
    }
    for head, body in defs.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [d.split("(")[0] for d in defs]


def register_views(kg) -> None:
    """facts, edges and classes as temporary views."""
    from ..plans.kg import edges

    kg.facts.createOrReplaceTempView("facts")
    edges(kg.facts).createOrReplaceTempView("edges")
    kg.classes.createOrReplaceTempView("classes")
