"""Mining temporal rules: candidates by support, then acceptance, refinement or rejection by confidence."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.kg import KnowledgeGraph, links, temporal_edges
from ..sources.tables import written
from .match import frequent_pairs, frequent_triples, match_linked_subjects, match_one_subject
from .score import RULE, exclusion_scores, score_linked_subjects, score_one_subject, score_ticks, with_scores

CLASSES = ("cx", "cy", "cz", "cw")
CONSTRAINTS = ("cid", *RULE, *CLASSES, "support", "n_pos", "n_neg", "n_unk", "confidence", "level", "origin")


@dataclass(frozen=True)
class Pruning:
    """Early abandonment. alpha: share of min_support seen before a rule is judged; beta: share of refine_conf below
    which it is hopeless; gamma: times min_support a property is seen before it is judged; undecided: whether rules
    not yet judged protect their properties; bound: 'none', 'wilson' or 'hoeffding' asks for an upper bound instead."""

    alpha: float = 0.5
    beta: float = 0.8
    gamma: float = 5.0
    stage1: bool = True
    stage2: bool = True
    undecided: str = "ignore"
    bound: str = "none"
    #: Whether a rule without a positive case among alpha * min_support cases of any verdict is hopeless too.
    no_positive: bool = True

    def __post_init__(self) -> None:
        if self.stage2 and not self.stage1:
            raise ValueError("properties are judged by abandoned rules: stage 2 needs stage 1")
        if self.undecided not in ("ignore", "protect") or self.bound not in ("none", "wilson", "hoeffding"):
            raise ValueError("undecided is 'ignore' or 'protect'; bound is 'none', 'wilson' or 'hoeffding'")


@dataclass(frozen=True)
class MinerConfig:
    min_support: int = 100
    accept_conf: float = 0.9
    refine_conf: float = 0.5
    level: str = "entity"
    inclusive_conf: bool = False
    patterns: tuple[str, ...] = ("a", "b")
    distinct_objects: bool = True
    reverse_facts: bool = False
    reverse_links: bool = True
    drop_inverted: bool = True
    refine_slots: tuple[str, ...] = ("x", "y", "z", "w")
    max_rules: int = 100_000
    #: Shares of the subjects that are seen before each decision; each round is a job, so few grow fast.
    rounds: tuple[float, ...] = (1 / 64, 1 / 16, 1 / 4, 43 / 64)

    def __post_init__(self) -> None:
        if not self.refine_conf <= self.accept_conf:
            raise ValueError("refine_conf must not be above accept_conf")
        if self.level not in ("entity", "fact"):
            raise ValueError("level is 'entity' or 'fact'")

    def above(self, limit: float) -> Column:
        c = F.col("confidence")
        return c >= limit if self.inclusive_conf else c > limit


def body_support(cfg: MinerConfig) -> int:
    """Subjects that a body needs: at entity level no fewer than the support; pairs of facts have no such bound."""
    return cfg.min_support if cfg.level == "entity" else 1


def candidate_counts(kg: KnowledgeGraph, cfg: MinerConfig) -> DataFrame:
    """Counts of every rule over frequent bodies, before any gate."""
    e = written(temporal_edges(kg.facts, cfg.reverse_facts, cfg.drop_inverted), "edges")
    out = exclusion_scores(e, cfg.level)
    if "a" in cfg.patterns:
        pairs = frequent_pairs(e, cfg.min_support, cfg.level)
        matches = match_one_subject(e, None, cfg.distinct_objects, pairs)
        out = out.unionByName(score_one_subject(matches, cfg.level))
    if "b" in cfg.patterns:
        l = written(links(kg.facts, cfg.reverse_links), "links")
        triples = written(frequent_triples(e, l, body_support(cfg)), "triples")
        out = out.unionByName(score_linked_subjects(match_linked_subjects(e, l, triples), cfg.level))
    return out


def mine_laid_ticks(edges: DataFrame, names: DataFrame, cfg: MinerConfig) -> DataFrame:
    """Accepted rules of one subject, unrefined, at entity level, over edges of single ticks that lie by subject (x, p, d, y, fact, ts_lo).

    Properties are numbers, in the order of their `names` (p, name).
    """
    counts = exclusion_scores(edges, "entity").unionByName(score_ticks(edges))
    for c in ("p1", "p2"):
        counts = counts.join(F.broadcast(names.select(F.col("p").alias(c), F.col("name").alias(f"name_{c}"))), c).drop(c).withColumnRenamed(f"name_{c}", c)
    found = written(as_constraints(counts, "entity", "mined").where(F.col("support") >= cfg.min_support), "candidates")
    if found.count() > cfg.max_rules:
        raise ValueError(f"more than {cfg.max_rules} candidate rules")
    return split_by_confidence(found, cfg)[0]


def rule_id(*more: str) -> Column:
    return F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("-")) for c in (*RULE, *more)])


def as_constraints(scored: DataFrame, level: str, origin: str) -> DataFrame:
    """Scored rules with the columns of a rule table; class columns default to '*'."""
    star = {c: F.lit("*") for c in CLASSES if c not in scored.columns}
    out = with_scores(scored).withColumns(star).withColumns({"level": F.lit(level), "origin": F.lit(origin)})
    return out.withColumn("cid", rule_id(*CLASSES)).select(*CONSTRAINTS)


def mine_candidates(kg: KnowledgeGraph, cfg: MinerConfig) -> DataFrame:
    """Rules with enough support."""
    return as_constraints(candidate_counts(kg, cfg), cfg.level, "mined").where(F.col("support") >= cfg.min_support)


def split_by_confidence(candidates: DataFrame, cfg: MinerConfig) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Accepted, to be refined, rejected."""
    accept = cfg.above(cfg.accept_conf)
    middle = cfg.above(cfg.refine_conf)
    return candidates.where(accept), candidates.where(middle & ~accept), candidates.where(~F.coalesce(middle, F.lit(False)))


def mine_constraints(kg: KnowledgeGraph, cfg: MinerConfig, pruning: Pruning | None = None, refine: bool = True) -> DataFrame:
    """Accepted rules, coarse and refined. Every candidate is scored once for support and confidence."""
    if pruning is None:
        found = written(mine_candidates(kg, cfg), "candidates")
    else:
        from .prune import mine_pruned

        found = mine_pruned(kg, cfg, pruning).candidates
    if found.count() > cfg.max_rules:
        raise ValueError(f"more than {cfg.max_rules} candidate rules")
    accepted, middle, _ = split_by_confidence(found, cfg)
    if not refine or middle.isEmpty():
        return accepted
    from .refine import refine as narrow

    return accepted.unionByName(narrow(kg, middle, cfg))


def update_scores(old: DataFrame, facts: DataFrame, touched: DataFrame, heads: tuple[str, ...] = ("before",)) -> DataFrame:
    """Subjects' verdicts after a change: those of touched subjects (x) anew, the others kept.

    `old` and the result: head, p1, d1, p2, d2, x, verdict for bodies of one subject.
    """
    e = temporal_edges(facts).join(touched.select("x").distinct(), "x", "left_semi")
    return old.join(touched.select("x").distinct(), "x", "left_anti").unionByName(subject_verdicts(e, heads))


def subject_verdicts(edges: DataFrame, heads: tuple[str, ...] = ("before",)) -> DataFrame:
    """head, p1, d1, p2, d2, x, verdict of each subject and pair of different slots, in both orders."""
    from .match import ordered_pairs, with_verdict

    pairs = ordered_pairs(match_one_subject(edges, False))
    out = None
    for h in heads:
        one = entity_verdicts_of(with_verdict(pairs, h), h)
        out = one if out is None else out.unionByName(one)
    return out


def entity_verdicts_of(verdicts: DataFrame, head: str) -> DataFrame:
    per = verdicts.groupBy("p1", "d1", "p2", "d2", "x").agg(F.min("verdict").alias("verdict"))
    return per.select(F.lit(head).alias("head"), "p1", "d1", "p2", "d2", "x", "verdict")


def describe(constraints: DataFrame) -> DataFrame:
    """Rules as text: head, then the atoms of the body."""
    s = lambda n: F.concat(F.col(f"p{n}"), F.when(F.col(f"d{n}") < 0, "^-1").otherwise(""))
    one = F.format_string("%s(x, y, t1), %s(x, z, t2)", s(1), s(2))
    two = F.format_string("%s(x, y, t1), %s(x, w), %s(w, z, t2)", s(1), s(0), s(2))
    body = F.when(F.col("pattern") == "b", two).otherwise(one)
    limits = F.concat_ws(", ", *[F.when(F.col(f"c{v}") != "*", F.concat(F.lit(f"{v} in "), F.col(f"c{v}"))) for v in "xyzw"])
    text = F.concat(F.col("head"), F.lit("(t1, t2) if "), body, F.when(limits != "", F.concat(F.lit(", "), limits)).otherwise(""))
    return constraints.select("cid", text.alias("rule"))


def save_constraints(constraints: DataFrame, path: str, form: str = "parquet") -> None:
    constraints.write.mode("overwrite").format(form).save(path)


def load_constraints(spark, path: str, form: str = "parquet") -> DataFrame:
    schema = "cid string, head string, pattern string, p0 string, d0 tinyint, p1 string, d1 tinyint, p2 string, d2 tinyint, cx string, cy string, cz string, cw string, support long, n_pos long, n_neg long, n_unk long, confidence double, level string, origin string"
    return spark.read.schema(schema).format(form).load(path).select(*CONSTRAINTS)


def compose(left: DataFrame, right: DataFrame) -> DataFrame:
    """Chains of `before` rules: t1 before t2 and t2 before t3 give t1 before t3; for rules of one subject, joined where slots meet."""
    pick = "head = 'before' and pattern <> 'b'"
    a = left.where(pick).select(F.col("cid").alias("cid_left"), "p1", "d1", F.col("p2").alias("pm"), F.col("d2").alias("dm"), F.col("confidence").alias("conf_left"))
    b = right.where(pick).select(F.col("cid").alias("cid_right"), F.col("p1").alias("pm"), F.col("d1").alias("dm"), "p2", "d2", F.col("confidence").alias("conf_right"))
    return a.join(b, ["pm", "dm"]).where("not (p1 = p2 and d1 = d2)").withColumn("head", F.lit("before"))
