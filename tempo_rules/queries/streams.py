"""Streaming queries, run over all that is there now, and joins on time; each has the batch SQL of the same answer."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.granule import micros
from ..operators import detect, joins
from ..operators.complete import split_by_time
from ..plans import project
from ..plans.kg import KnowledgeGraph
from ..sources.tables import table, written
from ..streaming import facts as st
from . import sqltext as t

HOUR = 3_600_000_000
DAY = 24 * HOUR

QUERIES, ORACLES = {}, {}


def _add(name, f, sql=None):
    QUERIES[name] = f
    if sql is not None:
        ORACLES[name] = sql


def _last(out, keys):
    """Of rows that updates wrote, the last of each key."""
    w = Window.partitionBy(*keys).orderBy(F.desc("batch_id"))
    return out.withColumn("k", F.row_number().over(w)).where("k = 1").drop("k", "batch_id")


def stream_rates(s, d):
    """Facts per property and day."""
    out = _last(st.drain(st.rates(st.event_facts(st.read_events(s, d))), "update"), ["lo", "p"])
    return out.select(micros(F.col("lo")).alias("lo"), "p", "n")


def stream_rates_sliding(s, d):
    out = _last(st.drain(st.rates(st.event_facts(st.read_events(s, d)), "1 day", "6 hours"), "update"), ["lo", "p"])
    return out.select(micros(F.col("lo")).alias("lo"), "p", "n")


_add("stream_rates", stream_rates, f"SELECT epoch_us(ts) // {DAY} * {DAY} AS lo, event_type AS p, count(*) AS n FROM events GROUP BY ALL")
_add("stream_rates_sliding", stream_rates_sliding, f"SELECT (epoch_us(ts) // {6 * HOUR} - k) * {6 * HOUR} AS lo, event_type AS p, count(*) AS n FROM events, (VALUES (0), (1), (2), (3)) v(k) GROUP BY ALL")


def stream_sessions(s, d):
    """Interval facts from sessions that the watermark has closed."""
    out = st.drain(st.session_facts(st.read_events(s, d)))
    return out.select("user_id", "event_type", micros(F.col("lo")).alias("lo"), micros(F.col("hi")).alias("hi"), "n")


_SESSIONS = f"""e AS (SELECT user_id, event_type, epoch_us(ts) AS tm, lag(epoch_us(ts)) OVER (PARTITION BY user_id, event_type ORDER BY ts) AS prev FROM events),
    r AS (SELECT *, sum(CASE WHEN tm - prev {{op}} {6 * HOUR} THEN 0 ELSE 1 END) OVER (PARTITION BY user_id, event_type ORDER BY tm ROWS UNBOUNDED PRECEDING) AS run FROM e),
    g AS (SELECT user_id, event_type, run, min(tm) AS lo, max(tm) AS hi, count(*) AS n FROM r GROUP BY ALL)"""
_add("stream_sessions", stream_sessions, f"WITH {_SESSIONS.format(op='<')} SELECT user_id, event_type, lo, hi, n FROM g WHERE hi + {6 * HOUR} <= (SELECT max(epoch_us(ts)) // 1000 * 1000 FROM events) - {DAY}")


def join_sessions(s, d):
    ev = table(s, d, "events").select("user_id", "event_type", micros(F.col("ts")).alias("at"))
    return joins.sessions(ev, ["user_id", "event_type"], "at", 6 * HOUR)


_add("join_sessions", join_sessions, f"WITH {_SESSIONS.format(op='<=')} SELECT user_id, event_type, lo, hi, n FROM g")


def stream_without_repeats(s, d):
    """The stream and itself once more: every fact counts once."""
    ev = st.event_facts(st.read_events(s, d))
    out = st.drain(st.without_repeats(ev.unionByName(st.event_facts(st.read_events(s, d)))))
    return out.groupBy("p").agg(F.count("*").alias("n"))


_add("stream_without_repeats", stream_without_repeats, "SELECT event_type AS p, count(*) AS n FROM events GROUP BY 1")

_RULE = [{"id": "N1", "head": "before", "slots": ["signup", "purchase"]}]


def stream_conflicts(s, d):
    """Arriving events against the earliest four fifths of the facts."""
    f = written(project.facts(s, d, ("K10",)), "facts")
    kg = KnowledgeGraph(split_by_time(f, 0.8)[0], s.createDataFrame([], "entity string, class string"))
    out = st.stream_conflicts(st.event_facts(st.read_events(s, d)), kg, detect.parse_rules(s, _RULE))
    return out.where("fact1 <> fact2").groupBy("cid").agg(F.count("*").alias("n"), F.count_distinct("new_fact").alias("n_facts"))


_add("stream_conflicts", stream_conflicts, f"""WITH f AS ({t.FAMILY['K10']}), n AS (SELECT *, row_number() OVER (ORDER BY ts_lo, fact_id) AS k, count(*) OVER () AS m FROM f), tr AS (SELECT * FROM n WHERE k <= floor(m * 0.8)),
    c AS (SELECT i.fact_id AS new_fact, i.fact_id AS fact1, j.fact_id AS fact2 FROM f i JOIN tr j ON i.s = j.s AND i.o <> j.o AND i.p = 'signup' AND j.p = 'purchase' AND ({t.verdict('before')}) = -1
    UNION SELECT j.fact_id, i.fact_id, j.fact_id FROM tr i JOIN f j ON i.s = j.s AND i.o <> j.o AND i.p = 'signup' AND j.p = 'purchase' AND ({t.verdict('before')}) = -1)
    SELECT 'N1' AS cid, count(*) AS n, count(DISTINCT new_fact) AS n_facts FROM c""")


def stream_pairs(s, d):
    """A purchase within a day after a signup of the user, both arriving."""
    ev = lambda p: st.event_facts(st.read_events(s, d)).where(F.col("p") == p)
    return st.drain(st.stream_stream_conflicts(ev("signup"), ev("purchase"), "1 day", "1 day")).select("x", "fact1", "fact2")


_add("stream_pairs", stream_pairs, f"WITH f AS ({t.FAMILY['K10']}) SELECT a.s AS x, a.fact_id AS fact1, b.fact_id AS fact2 FROM f a JOIN f b ON a.s = b.s AND a.p = 'signup' AND b.p = 'purchase' AND b.ts_lo > a.ts_lo AND b.ts_lo <= a.ts_lo + {DAY}")


def stream_verdicts(s, d):
    """Users that turn negative for before(signup, purchase)."""
    out = st.drain(st.running_verdicts(st.event_facts(st.read_events(s, d)).drop("at"), "signup", "purchase"))
    return out.select("x")


_add("stream_verdicts", stream_verdicts, "SELECT 'U:' || user_id AS x FROM events GROUP BY user_id HAVING max(ts) FILTER (event_type = 'signup') > min(ts) FILTER (event_type = 'purchase')")


def join_asof(s, d):
    """Each purchase with the user's last view at or before it."""
    ev = table(s, d, "events").select("event_id", "user_id", "event_type", micros(F.col("ts")).alias("at"))
    views = ev.where("event_type = 'view'").select("user_id", "at", F.col("event_id").alias("view_id"))
    return joins.asof_join(ev.where("event_type = 'purchase'").drop("event_type"), views, ["user_id"], "at", ["view_id"])


_add("join_asof", join_asof, """WITH v AS (SELECT * FROM events WHERE event_type = 'view'), p AS (SELECT * FROM events WHERE event_type = 'purchase')
    SELECT p.event_id, p.user_id, epoch_us(p.ts) AS at, (SELECT max_by(v.event_id, v.ts) FROM v WHERE v.user_id = p.user_id AND v.ts <= p.ts) AS view_id FROM p""")


def join_overlap(s, d):
    """Overlapping states of a user, from any days."""
    f = project.facts(s, d, ("K8",)).where("te_lo is not null").select("fact_id", F.split_part("s", F.lit(":"), F.lit(2)).alias("u"), F.col("ts_lo").alias("lo"), F.col("te_hi").alias("hi"))
    return joins.overlap_join(f, f, ["u"], "lo", "hi", 6 * HOUR).where("l_fact_id < r_fact_id").select(F.col("l_fact_id").alias("fact1"), F.col("r_fact_id").alias("fact2"))


_add("join_overlap", join_overlap, f"WITH f AS (SELECT fact_id, split_part(s, ':', 2) AS u, ts_lo AS lo, te_hi AS hi FROM ({t.FAMILY['K8']}) WHERE te_lo IS NOT NULL) SELECT a.fact_id AS fact1, b.fact_id AS fact2 FROM f a JOIN f b ON a.u = b.u AND a.fact_id < b.fact_id AND a.lo < b.hi AND b.lo < a.hi")


def join_salted(s, d):
    """Lines with their suppliers' nation, the line side spread over salts."""
    lines = table(s, d, "lineitem").select("l_suppkey", "l_orderkey", "l_quantity")
    sup = table(s, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    out = joins.salted_join(lines, sup, ["l_suppkey"], 8, "l_orderkey")
    return out.groupBy("s_nationkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


_add("join_salted", join_salted, "SELECT s_nationkey, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")


def cube_profile(s, d):
    """Facts by property and object kind, with all totals."""
    f = project.facts(s, d, ("K1", "K8", "K11", "K12"))
    return f.cube("p", "o_kind").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"))


_add("cube_profile", cube_profile, f"SELECT p, o_kind, CAST(grouping(p, o_kind) AS BIGINT) AS g, count(*) AS n FROM ({t.facts(('K1', 'K8', 'K11', 'K12'))}) GROUP BY CUBE (p, o_kind)")


def rollup_profile(s, d):
    f = project.facts(s, d, ("K8",)).withColumn("day", F.expr("ts_lo div 86400000000"))
    return f.rollup("o", "day").agg(F.count("*").alias("n"))


_add("rollup_profile", rollup_profile, f"SELECT o, ts_lo // {DAY} AS day, count(*) AS n FROM ({t.FAMILY['K8']}) GROUP BY ROLLUP (o, day)")


def topk_objects(s, d):
    """The three most frequent objects of each property."""
    f = project.facts(s, d, ("K2", "K3", "K8", "K12")).groupBy("p", "o").agg(F.count("*").alias("n"))
    return f.withColumn("place", F.row_number().over(Window.partitionBy("p").orderBy(F.desc("n"), "o"))).where("place <= 3")


_add("topk_objects", topk_objects, f"WITH f AS (SELECT p, o, count(*) AS n FROM ({t.facts(('K2', 'K3', 'K8', 'K12'))}) GROUP BY ALL) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY p ORDER BY n DESC, o) AS place FROM f) WHERE place <= 3")


def moving_rate(s, d):
    """Facts of each user in the day up to each fact, and the time since the one before."""
    f = project.facts(s, d, ("K9",)).select("fact_id", "s", "ts_lo")
    w = Window.partitionBy("s").orderBy("ts_lo")
    return f.withColumns({"n_day": F.count("*").over(w.rangeBetween(-DAY, 0)), "gap": F.col("ts_lo") - F.lag("ts_lo").over(w)})


_add("moving_rate", moving_rate, f"SELECT fact_id, s, ts_lo, count(*) OVER (PARTITION BY s ORDER BY ts_lo RANGE BETWEEN {DAY} PRECEDING AND CURRENT ROW) AS n_day, ts_lo - lag(ts_lo) OVER (PARTITION BY s ORDER BY ts_lo) AS gap FROM ({t.FAMILY['K9']})")


def pivot_states(s, d):
    """States of each user-day as columns."""
    f = project.facts(s, d, ("K8",)).withColumn("kind", F.split_part("o", F.lit(":"), F.lit(2)))
    return f.groupBy("s").pivot("kind", ["view", "click", "signup", "purchase", "error"]).agg(F.count(F.lit(1))).na.fill(0)


_add("pivot_states", pivot_states, f"SELECT s, {', '.join(f'''count(*) FILTER (o = 'EV:{k}') AS {k}''' for k in ('view', 'click', 'signup', 'purchase', 'error'))} FROM ({t.FAMILY['K8']}) GROUP BY s")


def facts_valid_at(s, d):
    """Time travel: properties of facts that may hold at noon of a day."""
    from ..plans.kg import lookup

    at = 1_705_320_000_000_000
    return lookup(project.facts(s, d, ("K4", "K7", "K8")), at=at).groupBy("p").agg(F.count("*").alias("n"))


_add("facts_valid_at", facts_valid_at, f"SELECT p, count(*) AS n FROM ({t.facts(('K4', 'K7', 'K8'))}) WHERE coalesce(ts_lo <= 1705320000000000, true) AND coalesce(te_hi > 1705320000000000, true) AND is_temporal GROUP BY p")


def approximate_overview(s, d):
    """Sketched counts beside exact ones: the error is reported, not the estimate."""
    from ..operators.evaluate import kg_overview

    f = written(project.facts(s, d), "facts")
    a, b = kg_overview(f, True), kg_overview(f).select(F.col("n_entities").alias("exact"))
    return a.join(F.broadcast(b), F.lit(True)).select((F.abs(F.col("n_entities") - F.col("exact")) < 0.15 * F.col("exact")).alias("close"), "n_facts")


_add("approximate_overview", approximate_overview, f"SELECT true AS close, count(*) AS n_facts FROM ({t.facts(project.WIDE)})")
