"""SQL texts that several oracles share: projections of the tables, and three-valued predicates as CASE."""

from __future__ import annotations

from collections.abc import Iterable

_POINT = "{0} AS ts_lo, {0} + 1 AS ts_hi, 0 AS ts_gran, {0} AS te_lo, {0} + 1 AS te_hi, 0 AS te_gran, true AS is_temporal"
_NONE = "CAST(NULL AS BIGINT) AS ts_lo, CAST(NULL AS BIGINT) AS ts_hi, CAST(NULL AS INT) AS ts_gran, CAST(NULL AS BIGINT) AS te_lo, CAST(NULL AS BIGINT) AS te_hi, CAST(NULL AS INT) AS te_gran, false AS is_temporal"
_O = "epoch_us(o_orderdate)"
_L = "epoch_us(l_shipdate)"
_K = "CAST(regexp_extract(props, '([0-9]+)', 1) AS BIGINT)"
_LINE = "l_orderkey || ':' || l_partkey || ':' || l_suppkey || ':' || l_linenumber || ':' || " + _L


def _row(fid: str, s: str, p: str, o: str, kind: str, time: str, src: str, body: str) -> str:
    return f"SELECT {fid} AS fact_id, {s} AS s, {p} AS p, {o} AS o, '{kind}' AS o_kind, {time}, '{src}' AS src FROM {body}"


def _static(fid: str, s: str, p: str, o: str, src: str, kind: str = "res", body: str | None = None) -> str:
    return _row(fid, s, p, o, kind, _NONE, src, body or src)


FAMILY = {
    "K1": _row("'K1:' || o_orderkey", "'C:' || o_custkey", "'placed_order'", "'O:' || o_orderkey", "res", _POINT.format(_O), "orders", "orders"),
    "K2": _row(
        "'K2:' || o_orderkey", "'C:' || o_custkey", "'ordered_with_priority'", "'PR:' || o_orderpriority", "lit",
        f"""{_O} AS ts_lo, {_O} + 1 AS ts_hi, 0 AS ts_gran,
        CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN epoch_us(date_trunc('day', o_orderdate)) WHEN o_orderpriority = '3-MEDIUM' THEN epoch_us(date_trunc('month', o_orderdate)) WHEN o_orderpriority = '5-LOW' THEN epoch_us(date_trunc('year', o_orderdate)) END AS te_lo,
        CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN epoch_us(date_trunc('day', o_orderdate) + INTERVAL 1 DAY) WHEN o_orderpriority = '3-MEDIUM' THEN epoch_us(date_trunc('month', o_orderdate) + INTERVAL 1 MONTH) WHEN o_orderpriority = '5-LOW' THEN epoch_us(date_trunc('year', o_orderdate) + INTERVAL 1 YEAR) END AS te_hi,
        CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 1 WHEN o_orderpriority = '3-MEDIUM' THEN 2 WHEN o_orderpriority = '5-LOW' THEN 3 END AS te_gran, true AS is_temporal""",
        "orders", "orders",
    ),
    "K3": _row("'K3:' || o_orderkey", "'O:' || o_orderkey", "'ordered_on'", "'ST:' || o_orderstatus", "lit", _POINT.format(_O), "orders", "orders"),
    "K4": _row("'K4:' || c_custkey", "'C:' || c_custkey", "'active_as'", "'SEG:' || c_mktsegment", "lit", "a AS ts_lo, a + 1 AS ts_hi, 0 AS ts_gran, b AS te_lo, b + 1 AS te_hi, 0 AS te_gran, true AS is_temporal", "orders", f"(SELECT c_custkey, c_mktsegment, min({_O}) AS a, max({_O}) AS b FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2)"),
    "K5": _row(f"'K5:' || {_LINE}", "'O:' || l_orderkey", "'contains_part'", "'P:' || l_partkey", "res", _POINT.format(_L), "lineitem", "lineitem"),
    "K6": _row(f"'K6:' || {_LINE}", "'O:' || l_orderkey", "'supplied_by'", "'S:' || l_suppkey", "res", _POINT.format(_L), "lineitem", "lineitem"),
    "K7": _row("'K7:' || s_suppkey", "'S:' || s_suppkey", "'supplier_active'", "'N:' || s_nationkey", "res", "a AS ts_lo, a + 1 AS ts_hi, 0 AS ts_gran, b AS te_lo, b + 1 AS te_hi, 0 AS te_gran, true AS is_temporal", "lineitem", f"(SELECT s_suppkey, s_nationkey, min({_L}) AS a, max({_L}) AS b FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2)"),
    "K8": _row(
        "'K8:' || event_id", "'UD:' || user_id || ':' || (t // 86400000000)", "'in_state'", "'EV:' || event_type", "res",
        "t AS ts_lo, t + 1 AS ts_hi, 0 AS ts_gran, e AS te_lo, e + 1 AS te_hi, CASE WHEN e IS NOT NULL THEN 0 END AS te_gran, true AS is_temporal", "events",
        "(SELECT event_id, user_id, event_type, epoch_us(ts) AS t, CASE WHEN event_type = 'error' THEN epoch_us(ts) + 21600000000 ELSE epoch_us(lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) END AS e FROM events)",
    ),
    "K9": _row("'K9:' || event_id", "'U:' || user_id", "'did'", f"'K:' || {_K}", "res", _POINT.format("epoch_us(ts)"), "events", "events"),
    "K10": _row("'K10:' || event_id", "'U:' || user_id", "event_type", f"'K:' || {_K}", "res", _POINT.format("epoch_us(ts)"), "events", "events"),
    "K11": _row("'K11:' || conv_id || ':' || turn", "'V:' || conv_id", "'said_' || role", "'T:' || conv_id || ':' || turn", "res", _POINT.format("turn"), "conversations", "conversations"),
    "K12": " UNION ALL ".join([
        _static("'K12:c:' || c_custkey", "'C:' || c_custkey", "'in_nation'", "'N:' || c_nationkey", "customer"),
        _static("'K12:s:' || s_suppkey", "'S:' || s_suppkey", "'in_nation'", "'N:' || s_nationkey", "supplier"),
        _static("'K12:n:' || n_nationkey", "'N:' || n_nationkey", "'in_region'", "'R:' || n_regionkey", "nation"),
        _static("'K12:t:' || p_partkey", "'P:' || p_partkey", "'made_as'", "'PT:' || p_type", "part"),
        _static("'K12:b:' || p_partkey", "'P:' || p_partkey", "'branded'", "'B:' || p_brand", "part"),
    ]),
    "K13": " UNION ALL ".join([
        _static("'K13:l:' || doc_id", "'D:' || doc_id", "'has_lang'", "'L:' || lang", "documents"),
        _static("'K13:s:' || doc_id", "'D:' || doc_id", "'from_source'", "'SRC:' || source", "documents"),
        _static("'K13:h:' || page_id", "'W:' || page_id", "'on_host'", "'H:' || regexp_extract(url, '://([^/?#]+)', 1)", "pages"),
        _static("'K13:q:' || doc_id", "'D:' || doc_id", "'labelled'", "'Q:' || quality", "labels", "lit"),
        _static("'K13:v:' || vec_id", "'E:' || vec_id", "'vec_label'", "'VL:' || label", "embeddings", "lit"),
    ]),
    "K14": " UNION ALL ".join([
        _static("'K14:' || event_id", "'U:' || user_id", f"'touched_' || ({_K} // 10)", f"'K:' || {_K}", "events"),
        _static("'K15:' || doc_id", "'D:' || doc_id", "'doc_' || lang || '_' || source", "'L:' || lang", "documents"),
    ]),
}

CLASSES = f"""
    SELECT DISTINCT entity, class FROM (
        SELECT 'C:' || c_custkey AS entity, 'SEG:' || c_mktsegment AS class FROM customer
        UNION ALL SELECT 'C:' || c_custkey, 'R:' || r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
        UNION ALL SELECT 'O:' || o_orderkey, 'ST:' || o_orderstatus FROM orders
        UNION ALL SELECT 'P:' || p_partkey, 'PT:' || p_type FROM part
        UNION ALL SELECT 'P:' || p_partkey, 'B:' || p_brand FROM part
        UNION ALL SELECT 'S:' || s_suppkey, 'R:' || r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
        UNION ALL SELECT 'EV:' || event_type, CASE WHEN event_type IN ('view', 'click') THEN 'browse' WHEN event_type IN ('signup', 'purchase') THEN 'deal' WHEN event_type = 'error' THEN 'fault' END FROM events
        UNION ALL SELECT 'K:' || {_K}, 'KD:' || ({_K} // 10) FROM events
    ) WHERE class IS NOT NULL
"""


def facts(families: Iterable[str]) -> str:
    return " UNION ALL ".join(FAMILY[f] for f in families)


def lt(a: str, b: str) -> str:
    return f"(CASE WHEN {a}_hi <= {b}_lo THEN true WHEN {b}_hi <= {a}_lo OR ({a}_lo = {b}_lo AND {a}_hi = {b}_hi) THEN false END)"


def eq(a: str, b: str) -> str:
    return f"(CASE WHEN {a}_lo = {b}_lo AND {a}_hi = {b}_hi THEN true WHEN {a}_hi <= {b}_lo OR {b}_hi <= {a}_lo THEN false END)"


def le(a: str, b: str) -> str:
    return f"({lt(a, b)} OR {eq(a, b)})"


def verdict(head: str, i: str = "i", j: str = "j") -> str:
    """CASE of a head over relations i and j with the six time columns."""
    a, b, c, d = f"{i}.ts", f"{i}.te", f"{j}.ts", f"{j}.te"
    precedes = lambda a, b, c, d: f"({lt(b, c)} OR ({eq(b, c)} AND (NOT {eq(a, c)} OR NOT {eq(b, d)})))"
    pos, neg = {
        "start": (eq(a, c), f"NOT {eq(a, c)} OR {lt(d, a)} OR {lt(b, c)}"),
        "finish": (eq(b, d), f"NOT {eq(b, d)} OR {lt(b, c)} OR {lt(d, a)}"),
        "before": (precedes(a, b, c, d), f"{lt(c, b)} OR {lt(d, b)} OR {lt(c, a)} OR {lt(d, a)}"),
        "disjoint": (f"{precedes(a, b, c, d)} OR {precedes(c, d, a, b)}", f"({lt(c, b)} AND ({le(b, d)} OR {le(a, c)})) OR ({lt(a, d)} AND ({le(d, b)} OR {le(c, a)}))"),
        "include": (f"{le(a, c)} AND {le(d, b)}", f"{lt(c, a)} OR {lt(d, a)} OR {lt(b, d)} OR {lt(b, c)}"),
    }[head]
    return f"CASE WHEN {pos} THEN 1 WHEN {neg} THEN -1 ELSE 0 END"

_DAY = 86_400_000_000


def old_snapshot(new: str) -> str:
    key = "TRY_CAST(split_part(fact_id, ':', 2) AS BIGINT)"
    fam = "split_part(fact_id, ':', 1)"
    moved = f"{fam} = 'K11' AND {key} % 7 = 0 AND p = 'said_system'"
    shift = f"CASE WHEN {fam} = 'K4' AND {key} % 97 = 0 THEN {-30 * _DAY} WHEN {fam} = 'K8' AND {key} % 97 = 0 THEN {2 * _DAY} WHEN {moved} THEN 10 ELSE 0 END"
    begin = f"CASE WHEN {moved} THEN 10 ELSE 0 END"
    return f"""
        SELECT fact_id, s, p, o, o_kind, ts_lo + {begin} AS ts_lo, ts_hi + {begin} AS ts_hi, ts_gran, te_lo + {shift} AS te_lo, te_hi + {shift} AS te_hi, te_gran, is_temporal, src FROM ({new})
        UNION ALL SELECT 'K3x:' || {key}, s, p, 'ST:X', o_kind, ts_lo, ts_hi, ts_gran, te_lo, te_hi, te_gran, is_temporal, src FROM ({new}) WHERE {fam} = 'K3' AND {key} % 97 = 0
    """


NOT_INVERTED = f"NOT coalesce({lt('te', 'ts')}, false)"


def edges(source: str, reverse: bool = False) -> str:
    """Temporal edges (x, y, d, ...) of a relation of facts, inverted ones left out."""
    one = f"SELECT s AS x, o AS y, 1 AS d, * FROM {source} WHERE is_temporal AND {NOT_INVERTED}"
    if not reverse:
        return one
    return f"{one} UNION ALL SELECT o AS x, s AS y, -1 AS d, * FROM {source} WHERE is_temporal AND o_kind = 'res' AND {NOT_INVERTED}"


def links(source: str) -> str:
    return f"""SELECT x, p AS p0, d AS d0, y, min(fact_id) AS link_fact FROM (
        SELECT s AS x, o AS y, 1 AS d, p, fact_id FROM {source} WHERE o_kind = 'res' UNION ALL SELECT o, s, -1, p, fact_id FROM {source} WHERE o_kind = 'res') GROUP BY 1, 2, 3, 4"""


def one_subject(e: str = "e") -> str:
    """Verdict rows (head, pattern, p0, p1, p2, x, fact1, fact2, v) of all rules over one subject, `never` apart."""
    parts = []
    for head in ("start", "finish", "disjoint", "before", "include"):
        on = {"disjoint": "i.p = j.p AND i.d = j.d AND i.fact_id < j.fact_id", "start": "((i.p, i.d) < (j.p, j.d) OR ((i.p, i.d) = (j.p, j.d) AND i.fact_id < j.fact_id)) AND i.fact_id <> j.fact_id"}
        on["finish"] = on["start"]
        parts.append(f"""SELECT '{head}' AS head, CASE WHEN i.p = j.p AND i.d = j.d THEN 'a_same' ELSE 'a_diff' END AS pattern, CAST(NULL AS VARCHAR) AS p0, CAST(NULL AS INT) AS d0, i.p AS p1, i.d AS d1, j.p AS p2, j.d AS d2,
            i.x AS x, i.fact_id AS fact1, j.fact_id AS fact2, i.y AS o1, j.y AS o2, {verdict(head)} AS v FROM {e} i JOIN {e} j ON i.x = j.x AND i.y <> j.y AND {on.get(head, 'i.fact_id <> j.fact_id')}""")
    return " UNION ALL ".join(parts)


def two_subjects(e: str = "e", l: str = "l") -> str:
    parts = []
    for head in ("start", "finish", "before", "include"):
        parts.append(f"""SELECT '{head}' AS head, 'b' AS pattern, k.p0, k.d0, i.p AS p1, i.d AS d1, j.p AS p2, j.d AS d2, i.x AS x, i.fact_id AS fact1, j.fact_id AS fact2, i.y AS o1, j.y AS o2, {verdict(head)} AS v
            FROM {e} i JOIN {l} k ON i.x = k.x AND k.x <> k.y JOIN {e} j ON j.x = k.y AND i.fact_id <> j.fact_id""")
    return " UNION ALL ".join(parts)


_RULE = "head, pattern, p0, d0, p1, d1, p2, d2"


def scores(level: str, v: str = "v", e: str = "e") -> str:
    """Counts of rules from verdict rows, with `never` from the edges."""
    rows = f"(SELECT {_RULE}, x, min(v) AS v FROM {v} GROUP BY ALL)" if level == "entity" else v
    neg = "count(*) FILTER (n > 1)" if level == "entity" else "CAST(sum((a * a - q) // 2) AS BIGINT)"
    return f"""SELECT {_RULE}, count(*) FILTER (v = 1) AS n_pos, count(*) FILTER (v = -1) AS n_neg, count(*) FILTER (v = 0) AS n_unk FROM {rows} GROUP BY {_RULE}
        UNION ALL SELECT 'never', 'a_same', NULL, NULL, p, d, p, d, count(*) FILTER (n = 1), {neg}, 0 FROM (
            SELECT x, p, d, count(*) AS n, sum(k) AS a, sum(k * k) AS q FROM (SELECT x, p, d, y, count(*) AS k FROM {e} GROUP BY ALL) GROUP BY ALL) GROUP BY p, d"""


CONFIDENCE = "round(n_pos / nullif(n_pos + n_neg, 0)::DOUBLE, 6)"


def hand_conflicts(rules: list[dict], e: str = "e", l: str = "l") -> str:
    """Conflicts (cid, x, fact1, fact2) of hand-written rules without classes."""
    slot = lambda t: (t[:-3], -1) if t.endswith("^-1") else (t, 1)
    parts = []
    for r in rules:
        (p1, d1), (p2, d2) = slot(r["slots"][0]), slot(r["slots"][-1])
        where = f"i.p = '{p1}' AND i.d = {d1} AND j.p = '{p2}' AND j.d = {d2} AND i.fact_id <> j.fact_id"
        if r["head"] != "never":
            where += f" AND ({verdict(r['head'])}) = -1"
        if r.get("link"):
            p0, d0 = slot(r["link"])
            parts.append(f"SELECT '{r['id']}' AS cid, i.x AS x, i.fact_id AS fact1, j.fact_id AS fact2 FROM {e} i JOIN {l} k ON i.x = k.x AND k.x <> k.y AND k.p0 = '{p0}' AND k.d0 = {d0} JOIN {e} j ON j.x = k.y WHERE {where}")
            continue
        if (p1, d1) == (p2, d2) and r["head"] in ("start", "finish", "disjoint", "never"):
            where += " AND i.fact_id < j.fact_id"
        parts.append(f"SELECT '{r['id']}' AS cid, i.x AS x, i.fact_id AS fact1, j.fact_id AS fact2 FROM {e} i JOIN {e} j ON i.x = j.x AND i.y <> j.y WHERE {where}")
    return " UNION ALL ".join(parts)
