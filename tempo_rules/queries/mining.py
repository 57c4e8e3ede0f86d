"""Queries that mine rules: candidates, acceptance, levels, refinement, pruning, composition."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..operators import mine, prune, refine
from ..operators.mine import MinerConfig, Pruning
from ..plans import project
from ..plans.project import SMALL
from ..sources.tables import MIN_SUPPORT, written
from . import sqltext as t

MIXED = ("K1", "K2", "K3", "K8", "K10", "K11")
LINKED = ("K1", "K3", "K4")
SUPPORT = 20

QUERIES, ORACLES = {}, {}
_OUT = ("head", "pattern", "p0", "d0", "p1", "p2", "n_pos", "n_neg", "n_unk")


def _add(name, f, sql=None):
    QUERIES[name] = f
    if sql is not None:
        ORACLES[name] = sql


def _cfg(d: str, **more) -> MinerConfig:
    return replace(MinerConfig(min_support=MIN_SUPPORT, patterns=("a",)), **more)


def _shown(rules):
    return rules.select(*_OUT, F.round("confidence", 6).alias("confidence"))


def _sql(families, level: str, where: str, linked: bool = False) -> str:
    more = f", l AS ({t.links('f')})" if linked else ""
    v = t.one_subject() + (f" UNION ALL {t.two_subjects()}" if linked else "")
    return f"""WITH f AS ({t.facts(families)}), e AS ({t.edges('f')}){more}, v AS ({v}), c AS ({t.scores(level)}), r AS (SELECT {', '.join(_OUT)}, {t.CONFIDENCE} AS confidence FROM c)
        SELECT * FROM r WHERE n_pos >= {SUPPORT}{where}"""


_add("mine_candidates", lambda s, d: _shown(mine.mine_candidates(project.graph(s, d, MIXED), _cfg(d))), _sql(MIXED, "entity", ""))
_add("mine_base", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d), refine=False)), _sql(MIXED, "entity", " AND confidence > 0.9"))
_add("mine_fact_level", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d, level="fact"), refine=False)), _sql(MIXED, "fact", " AND confidence > 0.9"))
_add("mine_linked", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, LINKED), _cfg(d, patterns=("a", "b")), refine=False)), _sql(LINKED, "entity", " AND confidence > 0.9", True))
_add("mine_pruned", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d), Pruning(), refine=False)), ORACLES["mine_base"])
_add("mine_stage1", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d), Pruning(stage2=False), refine=False)), ORACLES["mine_base"])
_add("mine_pruned_fact_level", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d, level="fact"), Pruning(), refine=False)), ORACLES["mine_fact_level"])
_add("mine_pruned_wilson", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d), Pruning(bound="wilson"), refine=False)), ORACLES["mine_base"])
_add("mine_linked_pruned", lambda s, d: _shown(mine.mine_constraints(project.graph(s, d, LINKED), _cfg(d, patterns=("a", "b")), Pruning(), refine=False)), ORACLES["mine_linked"])


#: Suppliers as subjects of hundreds of lines: the pairs that pruning is for.
HUBS = ("K1", "K3", "K6", "K7")
for _n, _p in (("mine_base_hubs", None), ("mine_pruned_hubs", Pruning()), ("mine_stage1_hubs", Pruning(stage2=False))):
    _add(_n, lambda s, d, p=_p: _shown(mine.mine_constraints(project.graph(s, d, HUBS), _cfg(d, reverse_facts=True), p, refine=False)),
         f"""WITH f AS ({t.facts(HUBS)}), e AS ({t.edges('f', True)}), v AS ({t.one_subject()}), c AS ({t.scores('entity')}), r AS (SELECT {', '.join(_OUT)}, {t.CONFIDENCE} AS confidence FROM c)
             SELECT * FROM r WHERE n_pos >= {SUPPORT} AND confidence > 0.9""")  # fmt: skip


#: Few temporal properties among very many static ones, where whole properties can be cut.
for _n, _p in (("mine_base_sparse", None), ("mine_stage1_sparse", Pruning(stage2=False)), ("mine_pruned_sparse", Pruning()), ("mine_pruned_strict", Pruning(no_positive=False))):
    _add(_n, lambda s, d, p=_p: _shown(mine.mine_constraints(project.graph(s, d, project.SPARSE), _cfg(d), p, refine=False)), _sql(project.SPARSE, "entity", " AND confidence > 0.9"))


def prune_log(s, d):
    """Which rules and properties were abandoned, when, and at what ratio (batches are by hash: no SQL form)."""
    return prune.mine_pruned(project.graph(s, d, MIXED), _cfg(d), Pruning()).log


def prune_log_sparse(s, d):
    """The same on the graph with very many static and few temporal properties."""
    return prune.mine_pruned(project.graph(s, d, project.SPARSE), _cfg(d), Pruning()).log


def prune_subset_check(s, d):
    """Survivors are among the base rules, with the same counts."""
    kg = project.graph(s, d, MIXED)
    base = written(mine.mine_candidates(kg, _cfg(d)), "base")
    kept = written(prune.mine_pruned(kg, _cfg(d), Pruning()).candidates, "kept")
    cols = ["cid", "n_pos", "n_neg", "n_unk"]
    extra = kept.select(cols).exceptAll(base.select(cols)).agg(F.count("*").alias("n_changed"))
    never = written(prune.mine_pruned(kg, _cfg(d), Pruning(alpha=1e9)).candidates, "never")
    diff = base.select(cols).exceptAll(never.select(cols)).union(never.select(cols).exceptAll(base.select(cols))).agg(F.count("*").alias("n_differ_without_pruning"))
    return extra.join(F.broadcast(diff), F.lit(True))


def rule_loss(s, d):
    """Candidate rules that pruning loses: hopeless ones by design, accepted ones by mistake."""
    from ..operators.evaluate import rule_loss

    kg = project.graph(s, d, MIXED)
    base = written(mine.mine_constraints(kg, _cfg(d), refine=False), "base")
    kept = written(mine.mine_constraints(kg, _cfg(d), Pruning(), refine=False), "kept")
    return rule_loss(base, kept)


def prune_sweep(s, d):
    """Evaluations, abandoned rules and properties, and accepted rules for settings of alpha, beta and gamma."""
    kg = project.graph(s, d, SMALL)
    rows = []
    for a, b, g in ((0.5, 0.8, 5.0), (0.25, 0.8, 5.0), (1.0, 0.8, 5.0), (0.5, 0.6, 5.0), (0.5, 1.0, 5.0), (0.5, 0.8, 1.0), (0.5, 0.8, 20.0)):
        out = prune.mine_pruned(kg, _cfg(d), Pruning(alpha=a, beta=b, gamma=g))
        rows.append((a, b, g, out.evaluated, out.dropped_rules, out.dropped_slots, out.candidates.where("confidence > 0.9").count()))
    return s.createDataFrame(rows, "alpha double, beta double, gamma double, evaluated long, dropped_rules int, dropped_properties int, accepted long")


for f in (prune_log, prune_log_sparse, prune_sweep):
    _add(f.__name__, f)
_add("prune_subset_check", prune_subset_check, "SELECT 0::BIGINT AS n_changed, 0::BIGINT AS n_differ_without_pruning")
_add("rule_loss", rule_loss, f"WITH b AS ({ORACLES['mine_base']}) SELECT count(*) AS n_base, 0::BIGINT AS n_lost, 0::BIGINT AS n_extra, 0.0 AS loss FROM b")

_REFINED = ("head", "cx", "cy", "cz", "n_pos", "n_neg", "n_unk")


def _coarse(s, d):
    kg = project.graph(s, d, ("K8",))
    cfg = _cfg(d)
    _, middle, _ = mine.split_by_confidence(mine.mine_candidates(kg, cfg), cfg)
    return kg, written(middle, "middle"), cfg


def refine_classes(s, d):
    """Counts of all class-restricted forms of the half-good rules."""
    kg, middle, cfg = _coarse(s, d)
    return refine.refined_scores(kg, middle, cfg).select(*_REFINED)


def case_study_refined(s, d):
    kg, middle, cfg = _coarse(s, d)
    return refine.refine(kg, middle, cfg).select(*_REFINED, F.round("confidence", 6).alias("confidence"))


def case_study_minimal(s, d):
    kg, middle, cfg = _coarse(s, d)
    return refine.refine(kg, middle, cfg, minimal=True).select(*_REFINED)


def _refined_sql(tail: str) -> str:
    """Half-good rules over K8 (found by SQL), with the classes of both objects."""
    wide = lambda c: f"(SELECT entity, class FROM k UNION ALL SELECT DISTINCT entity, '*' FROM k) {c}"
    return f"""WITH f AS ({t.FAMILY['K8']}), e AS ({t.edges('f')}), k AS ({t.CLASSES}), v AS ({t.one_subject()}), c AS ({t.scores('entity')}),
        half AS (SELECT head FROM c WHERE n_pos >= {SUPPORT} AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE > 0.5 AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE <= 0.9 AND head <> 'never'),
        two AS (SELECT head, v.x, fact1, fact2, v, y.class AS a, z.class AS b FROM v JOIN half USING (head) JOIN {wide('y')} ON v.o1 = y.entity JOIN {wide('z')} ON v.o2 = z.entity),
        s AS (SELECT head, x, v, CASE WHEN head IN ('start', 'finish', 'disjoint') THEN least(a, b) ELSE a END AS cy, CASE WHEN head IN ('start', 'finish', 'disjoint') THEN greatest(a, b) ELSE b END AS cz FROM two),
        g AS (SELECT head, cy, cz, x, min(v) AS v FROM s WHERE cy <> '*' OR cz <> '*' GROUP BY ALL),
        r AS (SELECT head, '*' AS cx, cy, cz, count(*) FILTER (v = 1) AS n_pos, count(*) FILTER (v = -1) AS n_neg, count(*) FILTER (v = 0) AS n_unk FROM g GROUP BY head, cy, cz)
        {tail}"""


_add("refine_classes", refine_classes, _refined_sql("SELECT * FROM r"))
_add("case_study_refined", case_study_refined, _refined_sql(f"SELECT *, {t.CONFIDENCE} AS confidence FROM r WHERE n_pos >= {SUPPORT} AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE > 0.9"))
_add("case_study_minimal", case_study_minimal, _refined_sql(f"""SELECT a.* FROM (SELECT * FROM r WHERE n_pos >= {SUPPORT} AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE > 0.9) a
    WHERE NOT EXISTS (SELECT 1 FROM r b WHERE b.n_pos >= {SUPPORT} AND b.n_pos / nullif(b.n_pos + b.n_neg, 0)::DOUBLE > 0.9 AND b.head = a.head AND (b.cy = '*' OR b.cy = a.cy) AND (b.cz = '*' OR b.cz = a.cz) AND (b.cy, b.cz) <> (a.cy, a.cz))"""))


def rules_composed(s, d):
    """Chains of two accepted `before` rules."""
    rules = written(mine.mine_constraints(project.graph(s, d, MIXED), _cfg(d, accept_conf=0.5), refine=False), "rules")
    return mine.compose(rules, rules).select("p1", "pm", "p2")


_add("rules_composed", rules_composed, f"""WITH r AS ({_sql(MIXED, 'entity', ' AND confidence > 0.5')}), b AS (SELECT * FROM r WHERE head = 'before')
    SELECT a.p1, a.p2 AS pm, c.p2 FROM b a JOIN b c ON a.p2 = c.p1 WHERE a.p1 <> c.p2""")


def rules_described(s, d):
    """Accepted rules as text."""
    rules = mine.mine_constraints(project.graph(s, d, SMALL), _cfg(d), refine=False)
    return mine.describe(rules).select("rule")


_add("rules_described", rules_described, f"""WITH r AS ({_sql(SMALL, 'entity', ' AND confidence > 0.9')})
    SELECT head || '(t1, t2) if ' || p1 || '(x, y, t1), ' || p2 || '(x, z, t2)' AS rule FROM r""")


def rules_sampled(s, d):
    """A fixed random sample of ten candidate rules for grading."""
    from ..operators.evaluate import sample_rules

    rules = mine.mine_candidates(project.graph(s, d, MIXED), _cfg(d))
    return sample_rules(rules, 10, 1).select("head", "p1", "p2")


_add("rules_sampled", rules_sampled, f"""WITH r AS ({_sql(MIXED, 'entity', '')}), k AS (SELECT *, head || '|' || pattern || '|-|-|' || p1 || '|1|' || p2 || '|1|*|*|*|*' AS cid FROM r)
    SELECT head, p1, p2 FROM k ORDER BY md5(cid || '#1'), cid LIMIT 10""")


def flagship(s, d):
    """Accepted and refined rules of the small graph."""
    return mine.mine_constraints(project.graph(s, d, SMALL), _cfg(d))


_add("mine_with_refinement", lambda s, d: flagship(s, d).select("head", "pattern", "p1", "p2", "cy", "cz", "n_pos", "n_neg", "n_unk", "origin"))
