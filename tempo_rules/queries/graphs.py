"""Queries over the projected graph, times, predicates and matches."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import granule as g
from ..functions.granule import TIME_COLUMNS, Granule, Interval
from ..functions.predicates import HEADS, within
from ..functions.sql_surface import install
from ..operators import match as m
from ..operators import mine, score
from ..plans import kg, project
from ..plans.project import SMALL, WIDE
from ..sources.tables import small, table, written
from . import sqltext as t

MONTH = 30 * 86_400_000_000
PAIRED = ("K1", "K2", "K3", "K8", "K11")
LINKED = ("K1", "K3", "K4")

#: Formats of time labels by priority or status of an order, for Spark and for SQL; others have no label.
PRIORITY_LABELS = {"1-URGENT": ("yyyy-MM-dd HH:mm:ss", "%Y-%m-%d %H:%M:%S"), "2-HIGH": ("yyyy-MM-dd", "%Y-%m-%d"), "3-MEDIUM": ("yyyy-MM", "%Y-%m"), "5-LOW": ("yyyy", "%Y")}
STATUS_LABELS = {"O": ("yyyy", "%Y"), "F": ("yyyy-MM", "%Y-%m"), "P": ("yyyy-MM-dd", "%Y-%m-%d")}

QUERIES, ORACLES = {}, {}


def _query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


_COLUMNS = "fact_id, s, p, o, o_kind, ts_lo, ts_hi, ts_gran, te_lo, te_hi, te_gran, is_temporal, src"
for _name, _families in {"kg_facts_orders": ("K1", "K2", "K3", "K4"), "kg_facts_lineitem": ("K5", "K6", "K7"), "kg_facts_events": ("K8", "K9", "K10"), "kg_facts_conversations": ("K11",), "kg_static": ("K12", "K13", "K14")}.items():
    QUERIES[_name] = lambda spark, d, fam=_families: project.facts(spark, d, fam)
    ORACLES[_name] = f"SELECT {_COLUMNS} FROM ({t.facts(_families)})"


@_query("kg_classes", t.CLASSES)
def kg_classes(spark, d):
    return project.classes(spark, d)


@_query("kg_overview", f"""
    WITH f AS ({t.facts(WIDE)}) SELECT count(*) AS n_facts, count(*) FILTER (is_temporal) AS n_temporal, count(DISTINCT p) AS n_properties, count(DISTINCT p) FILTER (is_temporal) AS n_temporal_properties,
    (SELECT count(DISTINCT e) FROM (SELECT s AS e FROM f UNION ALL SELECT o FROM f WHERE o_kind = 'res')) AS n_entities FROM f""")
def kg_overview(spark, d):
    from ..operators.evaluate import kg_overview

    return kg_overview(project.facts(spark, d))


@_query("kg_edges_reversed", f"""
    WITH f AS ({t.facts(WIDE)}) SELECT p, d, count(*) AS n, count(DISTINCT x) AS n_subjects FROM (SELECT s AS x, p, 1 AS d FROM f UNION ALL SELECT o, p, -1 FROM f WHERE o_kind = 'res') GROUP BY ALL""")
def kg_edges_reversed(spark, d):
    return kg.edges(project.facts(spark, d)).groupBy("p", "d").agg(F.count("*").alias("n"), F.count_distinct("x").alias("n_subjects"))


@_query("temporal_properties", f"SELECT p, count(*) AS n, count(*) FILTER (is_temporal) AS n_temporal FROM ({t.facts(WIDE)}) GROUP BY p")
def temporal_properties(spark, d):
    from ..operators.graph import temporal_properties

    return temporal_properties(project.facts(spark, d))


@_query("one_hop_facts", f"""
    WITH f AS ({t.facts(("K1", "K4", "K12"))}) SELECT p, count(*) AS n FROM f WHERE s IN (SELECT s FROM f WHERE p = 'active_as') GROUP BY p""")
def one_hop_facts(spark, d):
    from ..operators.graph import one_hop

    ps = spark.createDataFrame([("active_as",)], "p string")
    return one_hop(project.facts(spark, d, ("K1", "K4", "K12")), ps).groupBy("p").agg(F.count("*").alias("n"))


def _labels_sql() -> str:
    def label(c: str) -> str:
        start = f"strptime(CASE length({c}) WHEN 4 THEN {c} || '-01-01 00:00:00' WHEN 7 THEN {c} || '-01 00:00:00' WHEN 10 THEN {c} || ' 00:00:00' WHEN 19 THEN {c} END, '%Y-%m-%d %H:%M:%S')"
        end = f"CASE length({c}) WHEN 4 THEN epoch_us({start} + INTERVAL 1 YEAR) WHEN 7 THEN epoch_us({start} + INTERVAL 1 MONTH) WHEN 10 THEN epoch_us({start} + INTERVAL 1 DAY) WHEN 19 THEN epoch_us({start}) + 1 END"
        return f"epoch_us({start}) AS {c}_lo, {end} AS {c}_hi"

    text = lambda at, by, formats: f"CASE {by} " + " ".join(f"WHEN '{k}' THEN strftime({at}, '{v[1]}')" for k, v in formats.items()) + " ELSE '' END"
    later = "o_orderdate + to_days(CAST((o_orderkey % 5 - 2) * 20 AS INT))"
    labels = f"SELECT {text('o_orderdate', 'o_orderpriority', PRIORITY_LABELS)} AS a, {text(later, 'o_orderstatus', STATUS_LABELS)} AS b FROM orders"
    return f"""SELECT length_a, length_b, is_lt, is_eq, count(*) AS n FROM (
        SELECT length(a) AS length_a, length(b) AS length_b, {t.lt('a', 'b')} AS is_lt, {t.eq('a', 'b')} AS is_eq FROM (SELECT a, b, {label('a')}, {label('b')} FROM ({labels}))) GROUP BY ALL"""


@_query("time_granule_table", _labels_sql())
def time_granule_table(spark, d):
    """Labels of two dates of every order, as long as its priority and status say, compared."""
    def text(at, by, formats):
        out = F.lit("")
        for k, v in formats.items():
            out = F.when(F.col(by) == k, F.date_format(at, v[0])).otherwise(out)
        return out

    # orders of one date, priority, status and shift have the same labels: these are parsed once
    kinds = table(spark, d, "orders").groupBy("o_orderdate", "o_orderpriority", "o_orderstatus", F.expr("o_orderkey % 5 - 2").alias("shift")).agg(F.count("*").alias("n"))
    later = F.expr("o_orderdate + make_dt_interval(shift * 20)")
    df = kinds.select(text(F.col("o_orderdate"), "o_orderpriority", PRIORITY_LABELS).alias("a"), text(later, "o_orderstatus", STATUS_LABELS).alias("b"), "n").groupBy("a", "b").agg(F.sum("n").alias("n"))
    flat = [c.alias(f"{v}_{n}") for v in ("a", "b") for n, c in vars(g.granule(F.col(v))).items()]
    df = df.select("a", "b", "n", *flat)
    a, b = (Granule(*[F.col(f"{v}_{n}") for n in ("lo", "hi", "gran")]) for v in ("a", "b"))
    df = df.select("a", "b", "n", g.lt(a, b).alias("is_lt"), g.eq(a, b).alias("is_eq"))
    return df.groupBy(F.length("a").alias("length_a"), F.length("b").alias("length_b"), "is_lt", "is_eq").agg(F.sum("n").alias("n"))


_GRANULES = "SELECT fact_id AS id, s, te_lo AS {0}_lo, te_hi AS {0}_hi FROM (" + t.FAMILY["K2"] + ")"
_COMPARE = {"is_lt": t.lt("a", "b"), "is_le": t.le("a", "b"), "is_eq": t.eq("a", "b"), "is_ne": f"NOT {t.eq('a', 'b')}", "is_ge": t.le("b", "a"), "is_gt": t.lt("b", "a")}


@_query("time_compare_matrix", f"""
    WITH l AS ({_GRANULES.format('a')}), r AS ({_GRANULES.format('b')}), c AS (SELECT {', '.join(f'{v} AS {k}' for k, v in _COMPARE.items())} FROM l JOIN r ON l.s = r.s AND l.id <> r.id)
    SELECT {', '.join(_COMPARE)}, count(*) AS n FROM c GROUP BY ALL""")
def time_compare_matrix(spark, d):
    """All comparisons of the end granules of two orders of a customer: equal granules of a customer are counted before they are paired."""
    end = ["te_lo", "te_hi", "te_gran"]
    f = project.facts(spark, d, ("K2",)).groupBy("s", *end).agg(F.count("*").alias("n"))
    one = lambda v: f.select("s", F.struct(*[F.col(c).alias(c[3:]) for c in end]).alias(v), F.col("n").alias(f"n_{v}"))
    both = one("a").join(one("b"), "s").withColumn("n", F.col("n_a") * F.col("n_b") - F.when(F.col("a").eqNullSafe(F.col("b")), F.col("n_a")).otherwise(0)).where("n > 0")
    x, y = Granule.of(F.col("a")), Granule.of(F.col("b"))
    ops = {"is_lt": g.lt, "is_le": g.le, "is_eq": g.eq, "is_ne": g.ne, "is_ge": g.ge, "is_gt": g.gt}
    return both.select(*[f(x, y).alias(k) for k, f in ops.items()], "n").groupBy(*ops).agg(F.sum("n").alias("n"))


@_query("time_inverted", f"""
    SELECT p, count(*) FILTER (coalesce({t.lt('te', 'ts')}, false)) AS n_inverted, count(*) AS n FROM ({t.old_snapshot(t.facts(('K4', 'K8', 'K11')))}) GROUP BY p""")
def time_inverted(spark, d):
    old = project.old_snapshot(project.facts(spark, d, ("K4", "K8", "K11")))
    return old.groupBy("p").agg(F.count_if(g.is_inverted(Interval.columns())).alias("n_inverted"), F.count("*").alias("n"))


_K2 = f"WITH f AS ({t.FAMILY['K2']}), e AS ({t.edges('f')})"
_PAIR = "FROM e i JOIN e j ON i.x = j.x AND i.y <> j.y AND "


def _k2_pairs(spark, d):
    return m.match_one_subject(kg.temporal_edges(project.facts(spark, d, ("K2",))), True)


for _h in HEADS:
    QUERIES[f"pred_{_h}"] = lambda spark, d, h=_h: m.with_verdict(m.ordered_pairs(_k2_pairs(spark, d)), h).groupBy("verdict").agg(F.count("*").alias("n"))
    ORACLES[f"pred_{_h}"] = f"{_K2} SELECT verdict, count(*) AS n FROM (SELECT {t.verdict(_h)} AS verdict {_PAIR} i.fact_id <> j.fact_id) GROUP BY verdict"


@_query("pred_never", f"{_K2} SELECT n_objects, count(*) AS n FROM (SELECT x, count(DISTINCT y) AS n_objects FROM e GROUP BY x) GROUP BY 1")
def pred_never(spark, d):
    e = kg.temporal_edges(project.facts(spark, d, ("K2",)))
    return e.groupBy("x").agg(F.count_distinct("y").alias("n_objects")).groupBy("n_objects").agg(F.count("*").alias("n"))


@_query("pred_within", f"""{_K2}, p AS (SELECT j.ts_lo - (i.te_hi - 1) AS least, j.ts_hi - 1 - i.te_lo AS most {_PAIR} i.fact_id <> j.fact_id)
    SELECT verdict, count(*) AS n FROM (SELECT CASE WHEN least >= 0 AND most <= {MONTH} THEN 1 WHEN least > {MONTH} OR most < 0 THEN -1 ELSE 0 END AS verdict FROM p) GROUP BY verdict""")
def pred_within(spark, d):
    pairs = m.ordered_pairs(_k2_pairs(spark, d))
    return pairs.select(within(m.time_of(1), m.time_of(2), MONTH).alias("verdict")).groupBy("verdict").agg(F.count("*").alias("n"))


@_query("pred_sql_functions", f"{_K2} SELECT {', '.join(f'sum({t.verdict(h)})::BIGINT AS s_{h}' for h in HEADS)} {_PAIR} i.fact_id <> j.fact_id")
def pred_sql_functions(spark, d):
    install(spark)
    pairs = m.ordered_pairs(_k2_pairs(spark, d))
    pairs = pairs.select(m.time_of(1).struct().alias("i"), m.time_of(2).struct().alias("j"))
    return pairs.select(*[F.expr(f"sum(t_{h}(i, j))").cast("long").alias(f"s_{h}") for h in HEADS])


_E = f"WITH f AS ({t.facts(PAIRED)}), e AS ({t.edges('f')})"


@_query("match_a_same", f"{_E} SELECT i.p AS p1, count(*) AS n, count(DISTINCT i.x) AS n_subjects {_PAIR} i.p = j.p AND i.fact_id < j.fact_id GROUP BY 1")
def match_a_same(spark, d):
    return m.match(project.graph(spark, d, PAIRED), "a_same").groupBy("p1").agg(F.count("*").alias("n"), F.count_distinct("x").alias("n_subjects"))


@_query("match_a_diff", f"{_E} SELECT i.p AS p1, j.p AS p2, count(*) AS n, count(DISTINCT i.x) AS n_subjects {_PAIR} i.p < j.p GROUP BY 1, 2")
def match_a_diff(spark, d):
    return m.match(project.graph(spark, d, PAIRED), "a_diff").groupBy("p1", "p2").agg(F.count("*").alias("n"), F.count_distinct("x").alias("n_subjects"))


_B = f"WITH f AS ({t.facts(LINKED)}), e AS ({t.edges('f')}), l AS ({t.links('f')})"


@_query("match_b", f"""{_B} SELECT i.p AS p1, k.p0, k.d0, j.p AS p2, count(*) AS n FROM e i JOIN l k ON i.x = k.x AND k.x <> k.y JOIN e j ON j.x = k.y AND i.fact_id <> j.fact_id GROUP BY ALL""")
def match_b(spark, d):
    return m.match(project.graph(spark, d, LINKED), "b").groupBy("p1", "p0", "d0", "p2").agg(F.count("*").alias("n"))


@_query("observed_patterns", f"""{_E}, s AS (SELECT x, p, count(*) AS n FROM e GROUP BY ALL)
    SELECT a.p AS p1, b.p AS p2, count(*) AS n_subjects FROM s a JOIN s b ON a.x = b.x AND (a.p < b.p OR (a.p = b.p AND a.n > 1)) GROUP BY ALL""")
def observed_patterns(spark, d):
    return m.observed_patterns(kg.temporal_edges(project.facts(spark, d, PAIRED))).select("p1", "p2", "n_subjects")


_AT = 852_076_800_000_000


@_query("lookup_quad", f"SELECT fact_id, s, o FROM ({t.FAMILY['K4']}) WHERE p = 'active_as' AND o = 'SEG:BUILDING' AND ts_lo <= {_AT} AND te_hi > {_AT}")
def lookup_quad(spark, d):
    return kg.lookup(project.facts(spark, d, ("K4",)), p="active_as", o="SEG:BUILDING", at=_AT).select("fact_id", "s", "o")


_SCORED = ("head", "pattern", "p1", "p2", "n_pos", "n_neg", "n_unk")
_V = f"v AS ({t.one_subject()})"
for _level in ("entity", "fact"):
    def _scores(spark, d, level=_level):
        e = kg.temporal_edges(project.facts(spark, d, SMALL))
        out = score.score_one_subject(m.match_one_subject(e), level).unionByName(score.exclusion_scores(e, level))
        return score.with_scores(out).select(*_SCORED, F.round("confidence", 6).alias("confidence"))

    QUERIES[f"score_{_level}"] = _scores
    ORACLES[f"score_{_level}"] = f"WITH f AS ({t.facts(SMALL)}), e AS ({t.edges('f')}), {_V}, c AS ({t.scores(_level)}) SELECT {', '.join(_SCORED)}, {t.CONFIDENCE} AS confidence FROM c"


@_query("score_never", f"WITH f AS ({t.facts(('K1', 'K3', 'K6'))}), e AS ({t.edges('f', True)}) SELECT p, d, count(*) FILTER (n = 1) AS n_pos, count(*) FILTER (n > 1) AS n_neg FROM (SELECT x, p, d, count(DISTINCT y) AS n FROM e GROUP BY ALL) GROUP BY ALL")
def score_never(spark, d):
    e = kg.temporal_edges(project.facts(spark, d, ("K1", "K3", "K6")), reverse=True)
    return score.exclusion_scores(e).select(F.col("p1").alias("p"), F.col("d1").alias("d"), "n_pos", "n_neg")


@_query("score_worked_example", f"""
    WITH k AS (SELECT 'W:' || o_orderkey AS fact_id, 'C:' || o_custkey AS x, 'O:' || o_orderkey AS y, o_orderpriority = '5-LOW' AS whole_year, date_trunc('month', o_orderdate) AS a,
        CASE o_orderpriority WHEN '5-LOW' THEN date_trunc('year', o_orderdate) WHEN '1-URGENT' THEN date_trunc('month', o_orderdate) + INTERVAL 24 MONTH ELSE date_trunc('month', o_orderdate) + INTERVAL 3 MONTH END AS b FROM orders),
    e AS (SELECT fact_id, x, y, epoch_us(a) AS ts_lo, epoch_us(a + INTERVAL 1 MONTH) AS ts_hi, epoch_us(b) AS te_lo, CASE WHEN whole_year THEN epoch_us(b + INTERVAL 1 YEAR) ELSE epoch_us(b + INTERVAL 1 MONTH) END AS te_hi FROM k),
    v AS (SELECT i.x AS x, {t.verdict('disjoint')} AS v FROM e i JOIN e j ON i.x = j.x AND i.y <> j.y AND i.fact_id < j.fact_id),
    s AS (SELECT x, min(v) AS v FROM v GROUP BY x)
    SELECT f.*, n.* FROM (SELECT count(*) FILTER (v = 1) AS n_pos, count(*) FILTER (v = -1) AS n_neg, count(*) FILTER (v = 0) AS n_unk, round(count(*) FILTER (v = 1) / nullif(count(*) FILTER (v <> 0), 0)::DOUBLE, 6) AS fact_confidence FROM v) f,
        (SELECT count(*) FILTER (v = 1) AS entity_pos, count(*) FILTER (v = -1) AS entity_neg, round(count(*) FILTER (v = 1) / nullif(count(*) FILTER (v <> 0), 0)::DOUBLE, 6) AS entity_confidence FROM s) n""")
def score_worked_example(spark, d):
    """The worked example's count on careers of customers: an order is a membership from its month to a month or, if its priority is low, some time of the year."""
    rows = table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderpriority", F.date_trunc("month", "o_orderdate").alias("month"))
    # labels of a month and priority are parsed once
    until = F.when(F.col("o_orderpriority") == "5-LOW", F.date_format("month", "yyyy")).otherwise(F.date_format(F.add_months("month", F.when(F.col("o_orderpriority") == "1-URGENT", 24).otherwise(3)), "yyyy-MM"))
    labels = rows.select("month", "o_orderpriority").distinct().select(F.col("month").alias("m"), F.col("o_orderpriority").alias("pr"), F.date_format("month", "yyyy-MM").alias("a"), until.alias("b"))
    times = written(labels.select("m", "pr", *Interval(g.granule(F.col("a")), g.granule(F.col("b"))).named()), "times")
    rows = rows.join(small(times), F.col("month").eqNullSafe(F.col("m")) & F.col("o_orderpriority").eqNullSafe(F.col("pr")))
    key = lambda p, c: F.concat(F.lit(f"{p}:"), F.col(c).cast("string"))
    facts = rows.select(key("W", "o_orderkey").alias("fact_id"), key("C", "o_custkey").alias("s"), F.lit("member").alias("p"), key("O", "o_orderkey").alias("o"), F.lit("res").alias("o_kind"), *TIME_COLUMNS, F.lit(True).alias("is_temporal"), F.lit("orders").alias("src"))
    v = m.with_verdict(m.match_one_subject(kg.temporal_edges(facts), True), "disjoint")
    fact, entity = score.fact_scores(v), score.entity_scores(v)
    one = fact.select("n_pos", "n_neg", "n_unk", F.round("confidence", 6).alias("fact_confidence"))
    two = entity.select(F.col("n_pos").alias("entity_pos"), F.col("n_neg").alias("entity_neg"), F.round("confidence", 6).alias("entity_confidence"))
    return one.join(F.broadcast(two), F.lit(True))


@_query("score_tidy_time", f"""
    WITH f AS ({t.FAMILY['K2']}), k AS (SELECT fact_id, s AS x, o AS y, date_trunc('month', make_timestamp(ts_lo)) AS a, date_trunc('month', make_timestamp(te_lo)) AS b FROM f WHERE te_lo IS NOT NULL),
    e AS (SELECT fact_id, x, y, epoch_us(a) AS ts_lo, epoch_us(a + INTERVAL 1 MONTH) AS ts_hi, epoch_us(b) AS te_lo, epoch_us(b + INTERVAL 1 MONTH) AS te_hi FROM k)
    SELECT verdict, count(*) AS n FROM (SELECT {t.verdict('disjoint')} AS verdict FROM e i JOIN e j ON i.x = j.x AND i.y <> j.y AND i.fact_id < j.fact_id WHERE NOT coalesce(i.te_hi <= i.ts_lo, false) AND NOT coalesce(j.te_hi <= j.ts_lo, false)) GROUP BY 1""")
def score_tidy_time(spark, d):
    pairs = m.match_one_subject(kg.temporal_edges(kg.tidy(project.facts(spark, d, ("K2",)))), True)
    return m.with_verdict(pairs, "disjoint").groupBy("verdict").agg(F.count("*").alias("n"))


def _cost_sql(family: str, d: int) -> str:
    x = "s" if d > 0 else "o"
    return f"SELECT '{family}' AS family, CAST(sum(n * (n - 1)) AS BIGINT) AS pairs, CAST(sum(n * (n - 1)) * 6 AS BIGINT) AS evaluations FROM (SELECT {x}, count(*) AS n FROM ({t.FAMILY[family]}) GROUP BY 1)"


@_query("matching_cost", " UNION ALL ".join(_cost_sql(f, d) for f, d in (("K1", 1), ("K6", -1), ("K9", 1))))
def matching_cost(spark, d):
    out = None
    for f, way in (("K1", 1), ("K6", -1), ("K9", 1)):
        e = kg.edges(project.facts(spark, d, (f,))).where(F.col("d") == way)
        one = score.matching_cost(e).select(F.lit(f).alias("family"), F.col("pairs").cast("long").alias("pairs"), F.col("evaluations").cast("long").alias("evaluations"))
        out = one if out is None else out.union(one)
    return out


@_query("matching_cost_linked", f"""{_B}, n AS (SELECT x, count(*) AS n FROM e GROUP BY x) SELECT CAST(sum(a.n * b.n) AS BIGINT) AS pairs FROM n a JOIN l ON a.x = l.x JOIN n b ON b.x = l.y""")
def matching_cost_linked(spark, d):
    f = project.facts(spark, d, LINKED)
    return score.matching_cost(kg.temporal_edges(f), "b", kg.links(f)).select(F.col("pairs").cast("long").alias("pairs"))


@_query("update_scores", f"""
    WITH f AS ({t.FAMILY['K11']}), e AS ({t.edges('f')}), v AS ({t.one_subject()})
    SELECT head, p1, p2, min_v AS verdict, count(*) AS n FROM (SELECT head, p1, p2, x, min(v) AS min_v FROM v WHERE head = 'before' AND p1 <> p2 GROUP BY ALL) GROUP BY ALL""")
def update_scores(spark, d):
    new = project.facts(spark, d, ("K11",))
    old = mine.subject_verdicts(kg.temporal_edges(project.old_snapshot(new)))
    from ..operators.evaluate import wrong_fact_candidates

    touched = wrong_fact_candidates(project.old_snapshot(new), new).select(F.col("s").alias("x"))
    now = mine.update_scores(old, new, touched)
    return now.groupBy("head", "p1", "p2", "verdict").agg(F.count("*").alias("n"))


@_query("score_certificates", f"""
    WITH f AS ({t.facts(('K1', 'K2', 'K8', 'K11'))}), e AS ({t.edges('f')}), v AS ({t.one_subject()})
    SELECT head, p1, p2, min_v AS verdict, count(*) AS n FROM (SELECT head, p1, p2, x, min(v) AS min_v FROM v WHERE head IN ('before', 'include') AND p1 <> p2 GROUP BY ALL) GROUP BY ALL""")
def score_certificates(spark, d):
    from ..operators.certificates import entity_verdicts

    e = kg.temporal_edges(project.facts(spark, d, ("K1", "K2", "K8", "K11")))
    out = None
    for h in ("before", "include"):
        one = entity_verdicts(e, h).select(F.lit(h).alias("head"), "p1", "p2", "verdict")
        out = one if out is None else out.union(one)
    return out.groupBy("head", "p1", "p2", "verdict").agg(F.count("*").alias("n"))


@_query("absurd_hub_rule", f"""
    WITH f AS ({t.FAMILY['K6']}), e AS (SELECT o AS x, s AS y, * FROM f), v AS (SELECT i.x AS x, {t.verdict('disjoint')} AS v FROM e i JOIN e j ON i.x = j.x AND i.y <> j.y AND i.fact_id < j.fact_id)
    SELECT 'disjoint' AS head, CAST(count(*) FILTER (v = 1) AS BIGINT) AS fact_pos, CAST(count(*) FILTER (v = -1) AS BIGINT) AS fact_neg, (SELECT count(*) FROM (SELECT x FROM v GROUP BY x HAVING min(v) = 1)) AS entity_pos, (SELECT count(*) FROM (SELECT x FROM v GROUP BY x HAVING min(v) = -1)) AS entity_neg FROM v""")
def absurd_hub_rule(spark, d):
    e = kg.temporal_edges(project.facts(spark, d, ("K6",)), reverse=True).where("d = -1")
    v = m.with_verdict(m.match_one_subject(e, True), "disjoint")
    per = v.groupBy("x").agg(F.count_if(F.col("verdict") == 1).alias("p"), F.count_if(F.col("verdict") == -1).alias("n"), F.min("verdict").alias("v"))
    return per.agg(F.sum("p").alias("fact_pos"), F.sum("n").alias("fact_neg"), F.count_if(F.col("v") == 1).alias("entity_pos"), F.count_if(F.col("v") == -1).alias("entity_neg")).select(F.lit("disjoint").alias("head"), "fact_pos", "fact_neg", "entity_pos", "entity_neg")
