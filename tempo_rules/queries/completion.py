"""Queries that rank predicted properties, re-rank them by conflicts and measure the ranking."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import complete, detect, mine
from ..operators.evaluate import ranking_metrics
from ..plans import project
from ..plans.kg import KnowledgeGraph
from ..sources.tables import MIN_SUPPORT, written
from . import sqltext as t

RULE = [{"id": "N1", "head": "before", "slots": ["signup", "purchase"]}]

QUERIES, ORACLES = {}, {}


def _add(name, f, sql=None):
    QUERIES[name] = f
    if sql is not None:
        ORACLES[name] = sql


def _parts(s, d):
    """Training part: the earliest 80 percent; the rest split by time, mixed and split again by hash."""
    f = written(project.facts(s, d, ("K10",)), "facts")
    train, rest = complete.split_by_time(f, 0.8)
    valid, test = complete.split_by_time(rest, 0.5)
    return complete.resplit(train, valid, test)


_PARTS = f"""f AS ({t.FAMILY['K10']}), n AS (SELECT *, row_number() OVER (ORDER BY ts_lo, fact_id) AS k, count(*) OVER () AS m FROM f),
    tr AS (SELECT * FROM n WHERE k <= floor(m * 0.8)), re AS (SELECT *, CAST('0x' || substr(md5(fact_id || '#0'), 1, 8) AS BIGINT) / 4294967296.0 AS u FROM n WHERE k > floor(m * 0.8)),
    te AS (SELECT * FROM re WHERE u >= 0.5)"""
_CANDIDATES = f"{_PARTS}, pool AS (SELECT DISTINCT p AS cand FROM tr), c AS (SELECT te.fact_id AS qid, te.s, te.p, te.o, te.ts_lo, cand FROM te, pool)"
_FREQUENT = f"""{_CANDIDATES}, ranked AS (SELECT c.*, row_number() OVER (PARTITION BY qid ORDER BY coalesce(n2, 0) DESC, coalesce(n1, 0) DESC, coalesce(n0, 0) DESC, cand) AS rank FROM c
    LEFT JOIN (SELECT s, o, p, count(*) AS n2 FROM tr GROUP BY ALL) a ON a.s = c.s AND a.o = c.o AND a.p = c.cand LEFT JOIN (SELECT s, p, count(*) AS n1 FROM tr GROUP BY ALL) b ON b.s = c.s AND b.p = c.cand LEFT JOIN (SELECT p, count(*) AS n0 FROM tr GROUP BY ALL) g ON g.p = c.cand)"""
_RECENT = f"""{_CANDIDATES}, ranked AS (SELECT c.*, row_number() OVER (PARTITION BY c.qid ORDER BY t2 DESC NULLS LAST, t1 DESC NULLS LAST, c.cand) AS rank FROM c
    LEFT JOIN (SELECT qid, cand, max(tr.ts_lo) AS t2 FROM c JOIN tr ON tr.s = c.s AND tr.o = c.o AND tr.p = c.cand AND tr.ts_lo < c.ts_lo GROUP BY ALL) a ON a.qid = c.qid AND a.cand = c.cand
    LEFT JOIN (SELECT qid, cand, max(tr.ts_lo) AS t1 FROM c JOIN tr ON tr.s = c.s AND tr.p = c.cand AND tr.ts_lo < c.ts_lo GROUP BY ALL) b ON b.qid = c.qid AND b.cand = c.cand)"""


def resplit_counts(s, d):
    train, valid, test = _parts(s, d)
    n = lambda df, name: df.agg(F.lit(name).alias("part"), F.count("*").alias("n"))
    return n(train, "train").union(n(valid, "valid")).union(n(test, "test"))


_add("resplit_counts", resplit_counts, f"WITH {_PARTS} SELECT 'train' AS part, count(*) AS n FROM tr UNION ALL SELECT 'valid', count(*) FROM re WHERE u < 0.5 UNION ALL SELECT 'test', count(*) FROM te")

_SHOW = ("qid", "cand_p", "rank", "is_gold")


def rank_baseline(s, d):
    train, _, test = _parts(s, d)
    return complete.frequency_ranker(train, test).select(*_SHOW)


def rank_recency(s, d):
    train, _, test = _parts(s, d)
    return complete.recency_ranker(train, test).select(*_SHOW)


for _n, _f, _q in (("rank_baseline", rank_baseline, _FREQUENT), ("rank_recency", rank_recency, _RECENT)):
    _add(_n, _f, f"WITH {_q} SELECT qid, cand AS cand_p, rank, cand = p AS is_gold FROM ranked")


def _reranked(s, d, ranker):
    train, _, test = _parts(s, d)
    predictions = written(ranker(train, test), "predictions")
    kg = KnowledgeGraph(train, s.createDataFrame([], "entity string, class string"))
    flags = complete.conflict_flags(kg, predictions, detect.parse_rules(s, RULE))
    return complete.rerank(predictions, flags)


# a candidate signup is refuted by an earlier purchase of the user (of another object), a purchase by a later signup
_FLAGGED = """, flagged AS (SELECT r.*, CASE WHEN (cand = 'purchase' AND EXISTS (SELECT 1 FROM tr WHERE tr.s = r.s AND tr.p = 'signup' AND tr.o <> r.o AND tr.ts_lo > r.ts_lo))
    OR (cand = 'signup' AND EXISTS (SELECT 1 FROM tr WHERE tr.s = r.s AND tr.p = 'purchase' AND tr.o <> r.o AND tr.ts_lo < r.ts_lo)) THEN 1 ELSE 0 END AS flag FROM ranked r),
    moved AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY flag, rank) AS new_rank FROM flagged)"""


def rank_reranked(s, d):
    return _reranked(s, d, complete.frequency_ranker).select(*_SHOW, "flag", "new_rank")


_add("rank_reranked", rank_reranked, f"WITH {_FREQUENT}{_FLAGGED} SELECT qid, cand AS cand_p, rank, cand = p AS is_gold, flag, new_rank FROM moved")


def ranking_measures(s, d):
    """Both rankers before and after re-ranking."""
    out = None
    for name, ranker in (("frequency", complete.frequency_ranker), ("recency", complete.recency_ranker)):
        r = written(_reranked(s, d, ranker), "reranked")
        for stage, col in (("before", "rank"), ("after", "new_rank")):
            one = ranking_metrics(r, (1, 3, 10), col).withColumns({"ranker": F.lit(name), "stage": F.lit(stage)})
            out = one if out is None else out.unionByName(one)
    return out


def _measures(name: str, stage: str, col: str) -> str:
    return f"SELECT count(*) AS n_queries, round(100 * avg(1.0 / {col}), 6) AS mrr, round(100 * avg(({col} <= 1)::INT), 6) AS hits1, round(100 * avg(({col} <= 3)::INT), 6) AS hits3, round(100 * avg(({col} <= 10)::INT), 6) AS hits10, '{name}' AS ranker, '{stage}' AS stage FROM moved WHERE cand = p"


_add("ranking_metrics", ranking_measures, " UNION ALL ".join(f"SELECT * FROM (WITH {q}{_FLAGGED} {_measures(n, st, c)})" for n, q in (("frequency", _FREQUENT), ("recency", _RECENT)) for st, c in (("before", "rank"), ("after", "new_rank"))))


#: Orders with their lines and conversations: tables that obey rules, unlike random events.
RULED = ("K3", "K5", "K6", "K11")
_RULED_PARTS = f"""f AS ({t.facts(RULED)}), n AS (SELECT *, CAST('0x' || substr(md5(fact_id || '#1'), 1, 8) AS BIGINT) / 4294967296.0 AS u FROM f),
    tr AS (SELECT * FROM n WHERE u < 0.8), te AS (SELECT * FROM n WHERE u >= 0.8)"""
_BROKEN = "CASE ru.head " + " ".join(f"WHEN '{h}' THEN ({t.verdict(h)})" for h in ("start", "finish", "before", "disjoint", "include")) + " WHEN 'never' THEN -1 END = -1"
_MINED_FLAGS = f""", e AS ({t.edges('tr')}), v AS ({t.one_subject()}), sc AS ({t.scores('entity')}), ru AS (SELECT * FROM sc WHERE n_pos >= {MIN_SUPPORT} AND n_pos / nullif(n_pos + n_neg, 0)::DOUBLE > 0.9),
    nf AS (SELECT qid, cand, s AS x, cand AS p, o AS y, ts_lo, ts_lo + 1 AS ts_hi, 0 AS ts_gran, ts_lo AS te_lo, ts_lo + 1 AS te_hi, 0 AS te_gran FROM ranked),
    hit AS (SELECT i.qid, i.cand FROM nf i JOIN ru ON ru.p1 = i.p JOIN e j ON j.x = i.x AND j.p = ru.p2 AND i.y <> j.y WHERE {_BROKEN} UNION SELECT j.qid, j.cand FROM nf j JOIN ru ON ru.p2 = j.p JOIN e i ON i.x = j.x AND i.p = ru.p1 AND i.y <> j.y WHERE {_BROKEN}),
    flagged AS (SELECT r.*, (h.qid IS NOT NULL)::INT AS flag FROM ranked r LEFT JOIN hit h ON h.qid = r.qid AND h.cand = r.cand),
    moved AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY flag, rank) AS new_rank FROM flagged)"""
_MINED_RANKS = _FREQUENT.replace(_PARTS, _RULED_PARTS) + _MINED_FLAGS


def _reranked_mined(s, d):
    """Rules are mined from four fifths of the facts, and move the candidates for the others that break them.

    Facts at single instants are laid by subject once; with others among them, pairs are judged by their bounds.
    """
    cfg = mine.MinerConfig(min_support=MIN_SUPPORT, patterns=("a",))
    f = project.facts(s, d, RULED)
    u = complete.hash_share(F.col("fact_id"), 1)
    names = complete.property_names(f)
    laid = complete.laid_by_subject(f, names, u >= 0.8)
    if laid.where("span is not null").isEmpty():
        edges = laid.where("not held").select(F.col("s").alias("x"), "p", F.lit(1).cast("tinyint").alias("d"), F.col("o").alias("y"), "fact", "ts_lo")
        return complete.rerank_by_subject(laid, names, mine.mine_laid_ticks(edges, names, cfg))
    f = written(f, "facts")
    train, test = written(f.where(u < 0.8), "train"), f.where(u >= 0.8)
    kg = KnowledgeGraph(train, s.createDataFrame([], "entity string, class string"))
    rules = written(mine.mine_constraints(kg, cfg, refine=False), "rules")
    predictions = written(complete.frequency_ranker(train, test), "predictions")
    return complete.rerank(predictions, complete.conflict_flags(kg, predictions, rules)).select(*_SHOW, "flag", "new_rank")


_add("rank_reranked_mined", _reranked_mined, f"WITH {_MINED_RANKS} SELECT qid, cand AS cand_p, rank, cand = p AS is_gold, flag, new_rank FROM moved")


def ranking_measures_mined(s, d):
    """Measures before and after re-ranking by mined rules."""
    r = written(_reranked_mined(s, d).where("is_gold").select("is_gold", "rank", "new_rank"), "gold")
    one = lambda stage, col: ranking_metrics(r, (1, 3, 10), col).withColumns({"ranker": F.lit("frequency"), "stage": F.lit(stage)})
    return one("before", "rank").unionByName(one("after", "new_rank"))


_add("ranking_metrics_mined", ranking_measures_mined, " UNION ALL ".join(f"SELECT * FROM (WITH {_MINED_RANKS} {_measures('frequency', st, c)})" for st, c in (("before", "rank"), ("after", "new_rank"))))


def rank_entities(s, d):
    """The same with the object to be predicted: measures only."""
    train, _, test = _parts(s, d)
    return ranking_metrics(complete.frequency_ranker(train, test, "o"))


_add("rank_entities", rank_entities, f"""WITH {_PARTS}, pool AS (SELECT DISTINCT o AS cand FROM tr), c AS (SELECT te.fact_id AS qid, te.s, te.p, te.o, cand FROM te, pool),
    ranked AS (SELECT c.*, row_number() OVER (PARTITION BY qid ORDER BY coalesce(n2, 0) DESC, coalesce(n1, 0) DESC, coalesce(n0, 0) DESC, cand) AS rank FROM c
    LEFT JOIN (SELECT s, p, o, count(*) AS n2 FROM tr GROUP BY ALL) a ON a.s = c.s AND a.p = c.p AND a.o = c.cand LEFT JOIN (SELECT s, o, count(*) AS n1 FROM tr GROUP BY ALL) b ON b.s = c.s AND b.o = c.cand LEFT JOIN (SELECT o, count(*) AS n0 FROM tr GROUP BY ALL) g ON g.o = c.cand)
    SELECT count(*) AS n_queries, round(100 * avg(1.0 / rank), 6) AS mrr, round(100 * avg((rank <= 1)::INT), 6) AS hits1, round(100 * avg((rank <= 3)::INT), 6) AS hits3, round(100 * avg((rank <= 10)::INT), 6) AS hits10 FROM ranked WHERE cand = o""")
