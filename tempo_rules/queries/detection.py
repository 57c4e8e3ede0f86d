"""Queries that find conflicts, compare detectors and evaluate them on planted errors."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..operators import detect, evaluate, mine
from ..operators.graph import component_of
from ..operators.mine import MinerConfig
from ..plans import project
from ..plans.kg import KnowledgeGraph
from ..plans.project import ORDERS, SMALL
from ..sources.tables import MIN_SUPPORT, table, written
from . import sqltext as t

#: Families that the hand-written rules speak of.
RULED = ("K1", "K3", "K4", "K5", "K6", "K7", "K8", "K11")
LABELLED = ("K1", "K3", "K4", "K8", "K11")
SUPPORT = 20
HAND = detect.HANDWRITTEN
PLANTED = [r["id"] for r in HAND]

QUERIES, ORACLES = {}, {}


def _add(name, f, sql=None):
    QUERIES[name] = f
    if sql is not None:
        ORACLES[name] = sql


def _old(s, d, families=LABELLED) -> KnowledgeGraph:
    return KnowledgeGraph(project.old_snapshot(project.facts(s, d, families)), project.classes(s, d))


def _rules(s, *ids):
    return detect.parse_rules(s, [r for r in HAND if not ids or r["id"] in ids])


def _graph_sql(source: str, linked: bool = True) -> str:
    return f"f AS ({source}), e AS ({t.edges('f', True)})" + (f", l AS ({t.links('f')})" if linked else "")


def _hand(ids: tuple[str, ...]) -> str:
    return t.hand_conflicts([r for r in HAND if not ids or r["id"] in ids])


_LOAD = t.old_snapshot(t.facts(LABELLED))


def conflicts_pairs(s, d):
    return detect.detect_conflicts(_old(s, d), _rules(s, "H1", "H2", "H3", "H6")).select("cid", "x", "fact1", "fact2")


def conflicts_never(s, d):
    return detect.detect_conflicts(_old(s, d), _rules(s, "H4", "H5", "H9")).select("cid", "x", "fact1", "fact2")


def conflicts_linked(s, d):
    return detect.detect_conflicts(_old(s, d), _rules(s, "H7")).select("cid", "x", "fact1", "fact2", "link_fact")


for _n, _f, _ids in (("conflicts_pairs", conflicts_pairs, ("H1", "H2", "H3", "H6")), ("conflicts_never", conflicts_never, ("H4", "H5", "H9"))):
    _add(_n, _f, f"WITH {_graph_sql(_LOAD)}, c AS ({_hand(_ids)}) SELECT cid, x, fact1, fact2 FROM c")
_add("conflicts_linked", conflicts_linked, f"""WITH {_graph_sql(_LOAD)} SELECT 'H7' AS cid, i.x AS x, i.fact_id AS fact1, j.fact_id AS fact2, k.link_fact
    FROM e i JOIN l k ON i.x = k.x AND k.x <> k.y AND k.p0 = 'placed_order' AND k.d0 = 1 JOIN e j ON j.x = k.y WHERE i.p = 'active_as' AND i.d = 1 AND j.p = 'ordered_on' AND j.d = 1 AND i.fact_id <> j.fact_id AND ({t.verdict('include')}) = -1""")


def conflicts_class(s, d):
    """Overlaps of two states neither of which is a fault."""
    rules = detect.parse_rules(s, [{"id": f"R{i}", "head": "disjoint", "slots": ["in_state", "in_state"], "classes": {"y": a, "z": b}} for i, (a, b) in enumerate([("browse", "browse"), ("browse", "deal"), ("deal", "deal")])])
    return detect.detect_conflicts(_old(s, d), rules).select("cid", "x", "fact1", "fact2")


_add("conflicts_class", conflicts_class, f"""WITH {_graph_sql(_LOAD)}, k AS ({t.CLASSES}), c AS ({_hand(('H1',))}), n AS (SELECT c.*, least(a.class, b.class) AS ca, greatest(a.class, b.class) AS cb FROM c
    JOIN f i ON i.fact_id = c.fact1 JOIN f j ON j.fact_id = c.fact2 JOIN k a ON a.entity = i.o JOIN k b ON b.entity = j.o)
    SELECT CASE WHEN ca = 'browse' AND cb = 'browse' THEN 'R0' WHEN ca = 'browse' THEN 'R1' ELSE 'R2' END AS cid, x, fact1, fact2 FROM n WHERE ca IN ('browse', 'deal') AND cb IN ('browse', 'deal')""")


def handwritten_conflicts(s, d):
    kg = project.graph(s, d, RULED)
    return detect.detect_conflicts(kg, _rules(s)).groupBy("cid").agg(F.count("*").alias("n"), F.count_distinct("x").alias("n_subjects"))


_add("handwritten_conflicts", handwritten_conflicts, f"WITH {_graph_sql(t.facts(RULED))}, c AS ({_hand(())}) SELECT cid, count(*) AS n, count(DISTINCT x) AS n_subjects FROM c GROUP BY cid")


def conflict_profile(s, d):
    kg, rules = project.graph(s, d, RULED), _rules(s)
    return detect.conflict_profile(written(detect.detect_conflicts(kg, rules), "conflicts"), rules).select("cid", "head", "n", "share", "place")


_heads = ", ".join(f"('{r['id']}', '{r['head']}')" for r in HAND)
_add("conflict_profile", conflict_profile, f"""WITH {_graph_sql(t.facts(RULED))}, c AS ({_hand(())}), n AS (SELECT cid, count(*) AS n FROM c GROUP BY cid)
    SELECT cid, head, n, round(n / (SELECT sum(n) FROM n)::DOUBLE, 6) AS share, rank() OVER (ORDER BY n DESC) AS place FROM n JOIN (VALUES {_heads}) h(cid, head) USING (cid)""")


def conflict_overlap(s, d):
    """All rules against those that the data supports."""
    kg = project.graph(s, d, RULED)
    all_ = written(detect.detect_conflicts(kg, _rules(s)), "all")
    some = written(detect.detect_conflicts(_old(s, d, RULED), _rules(s, "H1", "H4", "H6")), "some")
    return detect.conflict_overlap(all_, some)


_PAIRS = "SELECT DISTINCT least(fact1, fact2) AS a, greatest(fact1, fact2) AS b FROM"
_add("conflict_overlap", conflict_overlap, f"""WITH {_graph_sql(t.facts(RULED))}, f2 AS ({t.old_snapshot(t.facts(RULED))}), e2 AS ({t.edges('f2', True)}), l2 AS ({t.links('f2')}),
    p AS ({_PAIRS} ({_hand(())})), q AS ({_PAIRS} ({t.hand_conflicts([r for r in HAND if r['id'] in ('H1', 'H4', 'H6')], 'e2', 'l2')}))
    SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM p INTERSECT SELECT * FROM q) UNION ALL SELECT 'first', count(*) FROM (SELECT * FROM p EXCEPT SELECT * FROM q) UNION ALL SELECT 'second', count(*) FROM (SELECT * FROM q EXCEPT SELECT * FROM p)""")


def conflict_share(s, d):
    """Flagged pairs among all pairs of facts of a subject, and the most flagging rule's share."""
    kg, rules = project.graph(s, d, ("K3", "K8", "K11")), _rules(s, "H1", "H2", "H3", "H4")
    from ..operators.match import match_one_subject
    from ..plans.kg import temporal_edges

    c = written(detect.detect_conflicts(kg, rules), "conflicts")
    n = detect.count_conflicts(c)
    all_ = match_one_subject(temporal_edges(kg.facts)).agg(F.count("*").alias("n_pairs"))
    return n.join(F.broadcast(all_), F.lit(True)).withColumn("share", F.round(F.try_divide(F.col("n_conflicts"), F.col("n_pairs")), 6))


_add("conflict_share", conflict_share, f"""WITH {_graph_sql(t.facts(('K3', 'K8', 'K11')))}, c AS ({_hand(('H1', 'H2', 'H3', 'H4'))}), n AS (SELECT count(*) AS n_conflicts FROM ({_PAIRS} c)),
    a AS (SELECT count(*) AS n_pairs FROM e i JOIN e j ON i.x = j.x AND i.y <> j.y AND i.d = 1 AND j.d = 1 AND i.fact_id <> j.fact_id AND (i.p < j.p OR (i.p = j.p AND i.fact_id < j.fact_id)))
    SELECT n_conflicts, n_pairs, round(n_conflicts / n_pairs::DOUBLE, 6) AS share FROM n, a""")


def self_conflicts(s, d):
    return detect.self_conflicts(_old(s, d).facts).select("fact_id", "p")


_add("self_conflicts", self_conflicts, f"SELECT fact_id, p FROM ({_LOAD}) WHERE is_temporal AND NOT ({t.NOT_INVERTED})")


def check_new_facts(s, d):
    """The planted errors as new facts, against the clean graph without them."""
    new = project.facts(s, d, LABELLED)
    wrong = written(evaluate.wrong_fact_candidates(project.old_snapshot(new), new), "wrong")
    kg = KnowledgeGraph(new.join(wrong.select("fact_id"), "fact_id", "left_anti"), project.classes(s, d))
    return detect.check_new_facts(kg, wrong, _rules(s, "H1", "H2", "H4", "H6", "H7")).groupBy("cid").agg(F.count("*").alias("n"), F.count_distinct("new_fact").alias("n_facts"))


_KEY = "s, p, o, ts_lo, ts_hi, ts_gran, te_lo, te_hi, te_gran"
_WRONG = f"SELECT * FROM old o WHERE NOT EXISTS (SELECT 1 FROM new n WHERE {' AND '.join(f'o.{k} IS NOT DISTINCT FROM n.{k}' for k in _KEY.split(', '))})"
_VERSIONS = f"new AS ({t.facts(LABELLED)}), old AS ({_LOAD}), w AS ({_WRONG})"
_CHECKED = ("H1", "H2", "H4", "H6", "H7")


def _against(first: str, second: str) -> str:
    out = []
    for r in (r for r in HAND if r["id"] in _CHECKED):
        q = t.hand_conflicts([r], "EI").replace("FROM EI i", f"FROM {first} i").replace("JOIN EI j", f"JOIN {second} j").replace(" AND i.fact_id < j.fact_id", "")
        if r["head"] in ("disjoint", "never"):
            q = q.replace("i.fact_id AS fact1, j.fact_id AS fact2", "least(i.fact_id, j.fact_id) AS fact1, greatest(i.fact_id, j.fact_id) AS fact2")
        out.append(q)
    return " UNION ALL ".join(out)


_add("check_new_facts", check_new_facts, f"""WITH {_VERSIONS}, f AS (SELECT * FROM new WHERE fact_id NOT IN (SELECT fact_id FROM w)), en AS ({t.edges('w', True)}), eo AS ({t.edges('f', True)}), l AS ({t.links('f')}),
    c AS (SELECT DISTINCT * FROM ({_against('en', 'eo')} UNION ALL {_against('eo', 'en')})), u AS (SELECT cid, x, fact1, fact2, fact1 AS new_fact FROM c UNION ALL SELECT cid, x, fact1, fact2, fact2 FROM c)
    SELECT cid, count(*) AS n, count(DISTINCT new_fact) AS n_facts FROM u WHERE new_fact IN (SELECT fact_id FROM w) GROUP BY cid""")


def component_whole(s, d):
    """All facts connected with one conversation."""
    f = project.facts(s, d, ("K11", "K12"))
    seeds = f.where("p = 'said_user'").select(F.min("s").alias("entity"))
    return component_of(f, seeds).groupBy("p").agg(F.count("*").alias("n"))


_add("component_whole", component_whole, f"WITH f AS ({t.FAMILY['K11']}) SELECT p, count(*) AS n FROM f WHERE s = (SELECT min(s) FROM f WHERE p = 'said_user') GROUP BY p")


def _labels(s, d):
    new = project.facts(s, d, LABELLED)
    wrong = evaluate.wrong_fact_candidates(project.old_snapshot(new), new)
    right = new.join(wrong.select("fact_id"), "fact_id", "left_anti")
    return written(evaluate.balanced_labels(wrong, right), "labels")


_LABELS = f"""{_VERSIONS}, need AS (SELECT p, count(*) AS need FROM w GROUP BY p), lab AS (SELECT fact_id, true AS is_wrong, p AS property FROM w UNION ALL SELECT fact_id, false, p FROM (
    SELECT n.fact_id, n.p, need, row_number() OVER (PARTITION BY n.p ORDER BY md5(n.fact_id), n.fact_id) AS k FROM new n JOIN need USING (p) WHERE n.fact_id NOT IN (SELECT fact_id FROM w)) WHERE k <= need)"""


def wrong_fact_candidates(s, d):
    new = project.facts(s, d, LABELLED)
    return evaluate.wrong_fact_candidates(project.old_snapshot(new), new).select("fact_id", "p")


_add("wrong_fact_candidates", wrong_fact_candidates, f"WITH {_VERSIONS} SELECT fact_id, p FROM w")
_add("balanced_labels", lambda s, d: _labels(s, d).select("fact_id", "is_wrong", "property"), f"WITH {_LABELS} SELECT * FROM lab")
_add("label_distribution", lambda s, d: evaluate.label_overview(_labels(s, d)), f"WITH {_LABELS}, p AS (SELECT property, count(*) FILTER (is_wrong) AS n_wrong, count(*) FILTER (NOT is_wrong) AS n_right FROM lab GROUP BY 1) SELECT *, rank() OVER (ORDER BY n_wrong DESC) AS place FROM p")


def component_subgraph(s, d):
    """Facts within two hops of the subjects of the labelled facts."""
    f = project.facts(s, d, ("K1", "K5", "K12"))
    new = project.facts(s, d, LABELLED)
    named = new.unionByName(project.old_snapshot(new)).select("fact_id", F.col("s").alias("entity"))
    seeds = named.join(_labels(s, d).select("fact_id"), "fact_id", "left_semi").select("entity")
    return component_of(f, seeds, 2).groupBy("p").agg(F.count("*").alias("n"))


_add("component_subgraph", component_subgraph, f"""WITH RECURSIVE {_LABELS}, cf AS ({t.facts(('K1', 'K5', 'K12'))}), g AS (SELECT DISTINCT s AS a, o AS b FROM cf WHERE o_kind = 'res' UNION SELECT DISTINCT o, s FROM cf WHERE o_kind = 'res'),
    named AS (SELECT fact_id, s FROM new UNION SELECT fact_id, s FROM old),
    r(entity, hop) AS (SELECT DISTINCT s, 0 FROM named WHERE fact_id IN (SELECT fact_id FROM lab) UNION SELECT g.b, r.hop + 1 FROM r JOIN g ON g.a = r.entity WHERE r.hop < 2)
    SELECT p, count(*) AS n FROM cf WHERE s IN (SELECT entity FROM r) GROUP BY p""")


def _mined_conflicts(s, d, level: str):
    kg = _old(s, d)
    cfg = replace(MinerConfig(min_support=MIN_SUPPORT, patterns=("a",)), level=level)
    rules = written(mine.mine_constraints(kg, cfg, refine=False), "rules")
    return rules, written(detect.detect_conflicts(kg, rules), "conflicts")


def _mined_sql(level: str) -> str:
    """Accepted rules over the old version, and their conflicts."""
    return f"""{_LABELS}, e AS ({t.edges('old')}), v AS ({t.one_subject()}), sc AS ({t.scores(level)}), ru AS (SELECT * FROM sc WHERE n_pos >= {SUPPORT} AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE > 0.9),
        nv AS (SELECT i.fact_id AS fact1, j.fact_id AS fact2, i.p FROM e i JOIN e j ON i.x = j.x AND i.p = j.p AND i.y <> j.y AND i.fact_id < j.fact_id),
        c AS (SELECT v.head || v.p1 || v.p2 AS cid, fact1, fact2 FROM v JOIN ru ON v.head = ru.head AND v.p1 = ru.p1 AND v.p2 = ru.p2 WHERE v = -1 UNION ALL SELECT 'never' || nv.p, fact1, fact2 FROM nv JOIN ru ON ru.head = 'never' AND ru.p1 = nv.p),
        hit AS (SELECT fact1 AS fact_id FROM c UNION SELECT fact2 FROM c), wr AS (SELECT DISTINCT fact_id FROM lab WHERE is_wrong)"""


_RECALL = "SELECT count(*) AS n_wrong, count(*) FILTER (fact_id IN (SELECT fact_id FROM hit)) AS n_found, round(count(*) FILTER (fact_id IN (SELECT fact_id FROM hit)) / count(*)::DOUBLE, 6) AS recall FROM wr"
for _n, _level in (("recall_mined", "entity"), ("recall_fact", "fact")):
    _add(_n, lambda s, d, level=_level: evaluate.recall(_mined_conflicts(s, d, level)[1], _labels(s, d)), f"WITH {_mined_sql(_level)} {_RECALL}")
_HAND_FOR = ("H1", "H2", "H3", "H4", "H6", "H9")
_add("recall_hand", lambda s, d: evaluate.recall(detect.detect_conflicts(_old(s, d), _rules(s, *_HAND_FOR)), _labels(s, d)),
     f"WITH {_LABELS}, e AS ({t.edges('old', True)}), c AS ({_hand(_HAND_FOR)}), hit AS (SELECT fact1 AS fact_id FROM c UNION SELECT fact2 FROM c), wr AS (SELECT DISTINCT fact_id FROM lab WHERE is_wrong) {_RECALL}")
_YIELD = "p AS (SELECT DISTINCT least(fact1, fact2) AS a, greatest(fact1, fact2) AS b FROM c) SELECT count(*) AS n_pairs, count(*) FILTER (a IN (SELECT fact_id FROM wr) OR b IN (SELECT fact_id FROM wr)) AS n_hits, round(count(*) FILTER (a IN (SELECT fact_id FROM wr) OR b IN (SELECT fact_id FROM wr)) / count(*)::DOUBLE, 6) AS yield FROM p"
for _n, _level in (("conflict_yield", "entity"), ("conflict_yield_fact", "fact")):
    _add(_n, lambda s, d, level=_level: evaluate.conflict_yield(_mined_conflicts(s, d, level)[1], _labels(s, d)), f"WITH {_mined_sql(_level)}, {_YIELD}")


def compare_levels(s, d):
    """Rules and conflicts of the entity level and the fact level, and their ratios."""
    one, two = (evaluate.summary(*_mined_conflicts(s, d, level), level) for level in ("entity", "fact"))
    return evaluate.compare_runs(one, two)


def _side(level: str) -> str:
    body = _mined_sql(level)
    return f"(WITH {body} SELECT (SELECT count(*) FROM ru) AS rules, (SELECT count(*) FROM c) AS conflicts)"


_add("compare_levels", compare_levels, f"""SELECT 'entity' AS run_a, a.rules AS rules_a, a.conflicts AS conflicts_a, 'fact' AS run_b, b.rules AS rules_b, b.conflicts AS conflicts_b,
    round(b.rules / a.rules::DOUBLE, 6) AS rules_ratio, round(b.conflicts / a.conflicts::DOUBLE, 6) AS conflicts_ratio FROM {_side('entity')} a, {_side('fact')} b""")


def _ratings(s, d):
    """Three raters of the labelled documents: quality, absence of toxicity, length."""
    l, docs = table(s, d, "labels"), table(s, d, "documents").select("doc_id", "n_chars")
    both = l.join(docs, "doc_id")
    long = F.when(F.col("n_chars") > 1000, "C").when(F.col("n_chars") > 300, "M").otherwise("W")
    grades = {"quality": F.when(F.col("quality") == 1, "C").otherwise("W"), "toxic": F.when(F.col("toxic") == 0, "C").otherwise("W"), "length": long}
    rows = F.explode(F.array(*[F.struct(F.lit(r).alias("rater"), g.alias("grade")) for r, g in grades.items()]))
    return both.select(F.col("doc_id").cast("string").alias("item"), rows.alias("r")).select("item", "r.*")


_RATINGS = """rt AS (SELECT doc_id, CASE WHEN quality = 1 THEN 'C' ELSE 'W' END AS a, CASE WHEN toxic = 0 THEN 'C' ELSE 'W' END AS b, CASE WHEN n_chars > 1000 THEN 'C' WHEN n_chars > 300 THEN 'M' ELSE 'W' END AS c FROM labels JOIN documents USING (doc_id)),
    n AS (SELECT doc_id, (a = 'C')::INT + (b = 'C')::INT + (c = 'C')::INT AS nc, (a = 'M')::INT + (b = 'M')::INT + (c = 'M')::INT AS nm, (a = 'W')::INT + (b = 'W')::INT + (c = 'W')::INT AS nw FROM rt)"""
_add("grades", lambda s, d: evaluate.grade_shares(evaluate.majority_grade(_ratings(s, d))), f"""WITH {_RATINGS}, g AS (SELECT CASE WHEN nc >= 2 THEN 'C' WHEN nw >= 2 THEN 'W' ELSE 'M' END AS g FROM n)
    SELECT count(*) AS n_items, round(count(*) FILTER (g = 'C') / count(*)::DOUBLE, 6) AS correct, round(count(*) FILTER (g = 'M') / count(*)::DOUBLE, 6) AS merit, round(count(*) FILTER (g = 'W') / count(*)::DOUBLE, 6) AS wrong, round(count(*) FILTER (g <> 'W') / count(*)::DOUBLE, 6) AS valuable FROM g""")
_add("fleiss_kappa", lambda s, d: evaluate.fleiss_kappa(_ratings(s, d)), f"""WITH {_RATINGS}, o AS (SELECT avg((nc * nc + nm * nm + nw * nw - 3) / 6.0) AS po, sum(nc) / sum(3)::DOUBLE AS pc, sum(nm) / sum(3)::DOUBLE AS pm, sum(nw) / sum(3)::DOUBLE AS pw FROM n)
    SELECT round((po - (pc * pc + pm * pm + pw * pw)) / (1 - (pc * pc + pm * pm + pw * pw)), 6) AS kappa FROM o""")


def planted_grades(s, d):
    """Mined rules against those that hold by construction."""
    listed = [("before", "said_system", "said_user"), ("before", "said_system", "said_assistant"), ("never", "ordered_on", "ordered_on"), ("include", "active_as", "placed_order"), ("never", "active_as", "active_as")]
    kg = project.graph(s, d, ("K1", "K3", "K4", "K8", "K11"))
    return evaluate.planted_report(mine.mine_constraints(kg, replace(MinerConfig(min_support=MIN_SUPPORT), patterns=("a",)), refine=False), listed)


_add("planted_grades", planted_grades)


def corrupted_facts(s, d):
    """Random replacement as in earlier work: facts changed by kind, every fiftieth by hash."""
    f = project.facts(s, d, ("K1", "K4"))
    out = None
    for kind in ("object", "property", "interval"):
        changed = evaluate.wrong_fact_candidates(evaluate.corrupt_facts(f, 50, kind), f).groupBy(F.lit(kind).alias("kind")).agg(F.count("*").alias("n"))
        out = changed if out is None else out.union(changed)
    return out


_add("corrupted_facts", corrupted_facts, f"""WITH n AS (SELECT count(*) AS n FROM ({t.facts(('K1', 'K4'))}) WHERE CAST('0x' || substr(md5(fact_id), 1, 8) AS BIGINT) % 50 = 0) SELECT kind, n FROM n, (VALUES ('object'), ('property'), ('interval')) k(kind)""")


def aligned_facts(s, d):
    """Customers renamed by a mapping table before versions are compared."""
    from ..operators.graph import align

    names = table(s, d, "customer").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("a"), F.concat(F.lit("Q:"), F.col("c_custkey").cast("string")).alias("b"))
    return align(project.facts(s, d, ("K4",)), names).select("fact_id", "s", "o")


_add("aligned_facts", aligned_facts, f"SELECT fact_id, 'Q:' || split_part(s, ':', 2) AS s, o FROM ({t.FAMILY['K4']})")
