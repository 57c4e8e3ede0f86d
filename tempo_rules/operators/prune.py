"""Mining with early abandonment: subjects come in batches, hopeless rules and slots leave between them.

A subject's pairs are all in its batch, so its verdicts are final there and counts of
rules that survive equal those of an unpruned run. Decisions need only the table of
rule counts, which is small and lives on the driver.
"""

from __future__ import annotations

import math
from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.kg import KnowledgeGraph, links, temporal_edges
from ..sources.tables import written
from .match import frequent_pairs, frequent_triples, heads_for, match_alive, match_linked_subjects
from .mine import MinerConfig, Pruning, as_constraints, body_support
from .score import ALL, BITS, RULE, exclusion_scores, linked_bit, score_linked_subjects, score_one_subject

Slot = tuple[str, int]
LOG = "round int, kind string, key string, n long, pos long, ratio double"


@dataclass
class Pruned:
    candidates: DataFrame
    log: DataFrame
    #: Head evaluations made, and those that an unpruned run would have made over the same bodies, as counted per subject or pair.
    evaluated: int
    dropped_rules: int
    dropped_slots: int


def _ceiling(pos: int, n: int, bound: str) -> float:
    """Estimate of the final ratio, or an upper bound of it (95 %)."""
    p = pos / n
    if bound == "wilson":
        z = 1.6448536269514722
        return (p + z * z / (2 * n) + z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)
    if bound == "hoeffding":
        return p + math.sqrt(math.log(1 / 0.05) / (2 * n))
    return p


def decide_rules(counts: dict[tuple, list[int]], cfg: MinerConfig, pr: Pruning) -> set[tuple]:
    """Rules seen often enough whose ratio is hopeless, or that have no positive case among as many of any verdict."""
    bad = set()
    enough = pr.alpha * cfg.min_support
    for rule, (pos, neg, unk) in counts.items():
        n = pos + neg
        if (n > enough and _ceiling(pos, n, pr.bound) < pr.beta * cfg.refine_conf) or (pr.no_positive and pos == 0 and n + unk > enough):
            bad.add(rule)
    return bad


def decide_slots(counts: dict[tuple, list[int]], bad: set[tuple], cfg: MinerConfig, pr: Pruning) -> set[Slot]:
    """Slots seen often enough in hopeless rules only."""
    seen: dict[Slot, dict[tuple, int]] = defaultdict(dict)
    spared: set[Slot] = set()
    doomed: set[Slot] = set()
    for rule, (pos, neg, unk) in counts.items():
        _, _, p0, d0, p1, d1, p2, d2 = rule
        body = (p0, d0, p1, d1, p2, d2) if (p1, d1) <= (p2, d2) else (p0, d0, p2, d2, p1, d1)
        judged = pos + neg > pr.alpha * cfg.min_support
        for slot in {(p1, d1), (p2, d2)}:
            seen[slot][body] = max(seen[slot].get(body, 0), pos + neg + unk)
            if rule in bad:
                doomed.add(slot)
            elif judged or pr.undecided == "protect":
                spared.add(slot)
    return {s for s, bodies in seen.items() if s in doomed - spared and sum(bodies.values()) >= pr.gamma * cfg.min_support}


def _bit(head: str, forward: bool) -> int:
    return BITS.get(head, BITS.get(f"{head}_{'12' if forward else '21'}", -1))


def _masks(pairs: list[tuple], bad: set[tuple]) -> list[tuple]:
    """Slot pairs with the heads still alive; disjointness is for pairs of one slot."""
    gone: dict[tuple, int] = defaultdict(int)
    for p in pairs:
        if p[:2] != p[2:4]:
            gone[p[:4]] |= 1 << BITS["disjoint"]
    for head, pattern, _, _, p1, d1, p2, d2 in bad:
        if pattern == "b" or head == "never":
            continue
        forward = (p1, d1) <= (p2, d2)
        key = (p1, d1, p2, d2) if forward else (p2, d2, p1, d1)
        gone[key] |= 1 << _bit(head, forward)
        if (p1, d1) == (p2, d2) and head in ("before", "include"):
            gone[key] |= 1 << _bit(head, False)
    return [(*p, ALL & ~gone[p]) for p in pairs]


def _few(bodies: DataFrame, cfg: MinerConfig) -> list[tuple]:
    """Bodies of rules, of which there may be at most max_rules."""
    rows = bodies.take(cfg.max_rules + 1)
    if len(rows) > cfg.max_rules:
        raise ValueError(f"more than {cfg.max_rules} rule bodies")
    return [tuple(r) for r in rows]


def mine_pruned(kg: KnowledgeGraph, cfg: MinerConfig, pr: Pruning) -> Pruned:
    spark = kg.facts.sparkSession
    edge = 0.0
    batch = F.lit(len(cfg.rounds) - 1)
    u = F.pmod(F.xxhash64("x"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    for k in range(len(cfg.rounds) - 2, -1, -1):
        edge = sum(cfg.rounds[: k + 1])
        batch = F.when(u < edge, k).otherwise(batch)
    e = written(temporal_edges(kg.facts, cfg.reverse_facts, cfg.drop_inverted).withColumn("batch", batch.cast("int")), "edges", ("batch",))
    whole = e.drop("batch")
    pairs = _few(frequent_pairs(whole, cfg.min_support, cfg.level), cfg) if "a" in cfg.patterns else []
    l = triples = None
    if "b" in cfg.patterns:
        l = written(links(kg.facts, cfg.reverse_links), "links")
        triples = _few(frequent_triples(whole, l, body_support(cfg)).select("p0", "d0", "p1", "d1", "p2", "d2"), cfg)
    counts: dict[tuple, list[int]] = defaultdict(lambda: [0, 0, 0])
    bad: set[tuple] = set()
    cut: set[Slot] = set()
    log: list[tuple] = []
    evaluated = 0
    for k in range(len(cfg.rounds)):
        own = e.where(F.col("batch") == k).drop("batch")
        other = whole
        if cut:
            gone = F.broadcast(spark.createDataFrame(sorted(cut), "p string, d tinyint"))
            own, other = own.join(gone, ["p", "d"], "left_anti"), whole.join(gone, ["p", "d"], "left_anti")
        live = [p for p in _masks([p for p in pairs if (p[0], p[1]) not in cut and (p[2], p[3]) not in cut], bad) if p[4]]
        found = exclusion_scores(own, cfg.level)
        if live:
            mask = spark.createDataFrame(live, "p1 string, d1 tinyint, p2 string, d2 tinyint, mask long")
            matches = match_alive(own, mask, cfg.distinct_objects)
            found = found.unionByName(score_one_subject(matches, cfg.level, F.col("mask")))
        if triples:
            heads: dict[tuple, int] = defaultdict(lambda: sum(1 << linked_bit(h) for h in heads_for("b")))
            for r in bad:
                if r[1] == "b":
                    heads[r[2:]] &= ~(1 << linked_bit(r[0]))
            open_ = [(*t, heads[t]) for t in triples if heads[t] and (t[2], t[3]) not in cut and (t[4], t[5]) not in cut]
            if open_:
                t = spark.createDataFrame(open_, "p0 string, d0 tinyint, p1 string, d1 tinyint, p2 string, d2 tinyint, mask long")
                found = found.unionByName(score_linked_subjects(match_linked_subjects(own, l, t, other), cfg.level, mask=F.col("mask")))
        for r in found.collect():
            rule = tuple(r[c] for c in RULE)
            evaluated += r["n_pos"] + r["n_neg"] + r["n_unk"]
            if rule in bad:
                continue
            for i, c in enumerate(("n_pos", "n_neg", "n_unk")):
                counts[rule][i] += r[c]
        if len(counts) > cfg.max_rules:
            raise ValueError(f"more than {cfg.max_rules} rules")
        if k == len(cfg.rounds) - 1:
            break
        if pr.stage1:
            now = decide_rules(counts, cfg, pr) - bad
            bad |= now
            log += [(k, "rule", "|".join("-" if x is None else str(x) for x in r), sum(counts[r]), counts[r][0], counts[r][0] / max(1, sum(counts[r][:2]))) for r in sorted(now, key=str)]
        if pr.stage2:
            new = decide_slots(counts, bad, cfg, pr) - cut
            cut |= new
            log += [(k, "property", f"{p}|{d}", sum(sum(c) for r, c in counts.items() if (p, d) in ((r[4], r[5]), (r[6], r[7]))), 0, None) for p, d in sorted(new)]
    gone = lambda r: r in bad or (r[4], r[5]) in cut or (r[6], r[7]) in cut
    kept = [(*r, *c) for r, c in counts.items() if not gone(r)]
    schema = "head string, pattern string, p0 string, d0 tinyint, p1 string, d1 tinyint, p2 string, d2 tinyint, n_pos long, n_neg long, n_unk long"
    out = as_constraints(spark.createDataFrame(kept, schema), cfg.level, "mined").where(F.col("support") >= cfg.min_support)
    return Pruned(out, spark.createDataFrame(log, LOG), evaluated, len(bad), len(cut))

