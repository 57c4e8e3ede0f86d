"""Measures: recall of wrong facts, grades and agreement, overviews, run comparison, ranking."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.granule import TIME_COLUMNS

GRADES = ("C", "M", "W")


def _in_conflict(conflicts: DataFrame) -> DataFrame:
    return conflicts.select(F.explode(F.array("fact1", "fact2")).alias("fact_id")).distinct()


def recall(conflicts: DataFrame, labels: DataFrame) -> DataFrame:
    """Share of facts labelled wrong that some conflict contains. Precision isn't given: labels cover few facts."""
    wrong = labels.where("is_wrong").select("fact_id").distinct()
    hit = wrong.join(_in_conflict(conflicts).withColumn("hit", F.lit(1)), "fact_id", "left")
    return hit.agg(F.count("*").alias("n_wrong"), F.count("hit").alias("n_found")).withColumn("recall", F.round(F.try_divide(F.col("n_found"), F.col("n_wrong")), 6))


def conflict_yield(conflicts: DataFrame, labels: DataFrame) -> DataFrame:
    """How many flagged pairs hold a fact labelled wrong."""
    wrong = labels.where("is_wrong").select(F.col("fact_id").alias("wf")).distinct()
    pair = conflicts.select(F.least("fact1", "fact2").alias("f1"), F.greatest("fact1", "fact2").alias("f2")).distinct()
    hits = pair.withColumn("wf", F.explode(F.array("f1", "f2"))).join(wrong, "wf", "left_semi").select("f1", "f2").distinct()
    n = pair.agg(F.count("*").alias("n_pairs"))
    return n.join(F.broadcast(hits.agg(F.count("*").alias("n_hits"))), F.col("n_hits") <= F.col("n_pairs")).withColumn("yield", F.round(F.try_divide(F.col("n_hits"), F.col("n_pairs")), 6))


def majority_grade(ratings: DataFrame) -> DataFrame:
    """Grade of each item by most raters; without a majority: some merit."""
    n = {g: F.count_if(F.col("grade") == g) for g in GRADES}
    most = F.when(2 * n["C"] > F.count("*"), "C").when(2 * n["W"] > F.count("*"), "W").otherwise("M")
    return ratings.groupBy("item").agg(most.alias("grade"))


def grade_shares(grades: DataFrame) -> DataFrame:
    share = lambda *g: F.round(F.count_if(F.col("grade").isin(*g)) / F.count("*"), 6)
    return grades.agg(F.count("*").alias("n_items"), share("C").alias("correct"), share("M").alias("merit"), share("W").alias("wrong"), share("C", "M").alias("valuable"))


def fleiss_kappa(ratings: DataFrame) -> DataFrame:
    """Agreement of raters beyond chance; null where chance agreement is complete."""
    per = ratings.groupBy("item").agg(F.count("*").alias("n"), *[F.count_if(F.col("grade") == g).alias(g) for g in GRADES])
    agree = (sum((F.col(g) * F.col(g) for g in GRADES), F.lit(0)) - F.col("n")) / (F.col("n") * (F.col("n") - 1))
    shares = per.where("n > 1").agg(F.avg(agree).alias("observed"), *[(F.sum(g) / F.sum("n")).alias(g) for g in GRADES])
    chance = sum((F.col(g) * F.col(g) for g in GRADES), F.lit(0.0))
    return shares.select(F.round(F.try_divide(F.col("observed") - chance, 1 - chance), 6).alias("kappa"))


def sample_rules(rules: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """A fixed random sample of rules, for grading."""
    return rules.orderBy(F.md5(F.concat(F.col("cid"), F.lit(f"#{seed}"))), "cid").limit(n)


def kg_overview(facts: DataFrame, approximate: bool = False) -> DataFrame:
    """Entities (subjects and resource objects), facts and properties, temporal and other."""
    count = (lambda c: F.approx_count_distinct(c)) if approximate else (lambda c: F.count_distinct(c))
    per = facts.agg(F.count("*").alias("n_facts"), F.count_if("is_temporal").alias("n_temporal"), count("p").alias("n_properties"), F.count_distinct(F.when(F.col("is_temporal"), F.col("p"))).alias("n_temporal_properties"))
    both = facts.select(F.col("s").alias("e")).union(facts.where("o_kind = 'res'").select("o"))
    return per.join(F.broadcast(both.agg(count("e").alias("n_entities"))), F.lit(True))


def label_overview(labels: DataFrame) -> DataFrame:
    """Wrong and right facts of every property, and the property's place by wrong ones."""
    per = labels.groupBy("property").agg(F.count_if("is_wrong").alias("n_wrong"), F.count_if(~F.col("is_wrong")).alias("n_right"))
    return per.withColumn("place", F.rank().over(Window.orderBy(F.desc("n_wrong"))))


def wrong_fact_candidates(old: DataFrame, new: DataFrame) -> DataFrame:
    """Facts of the old version that the new one hasn't: same subject, property, object and interval."""
    key = ["s", "p", "o", *TIME_COLUMNS]
    on = None
    for k in key:
        c = old[k].eqNullSafe(new[k])
        on = c if on is None else on & c
    return old.join(new, on, "left_anti")


def balanced_labels(wrong: DataFrame, correct: DataFrame) -> DataFrame:
    """Wrong facts and, property by property, as many correct ones, in a fixed random order."""
    need = wrong.groupBy("p").agg(F.count("*").alias("need"))
    w = Window.partitionBy("p").orderBy(F.md5("fact_id"), "fact_id")
    right = correct.join(need, "p").withColumn("k", F.row_number().over(w)).where("k <= need")
    return wrong.select("fact_id", F.lit(True).alias("is_wrong"), F.col("p").alias("property")).union(right.select("fact_id", F.lit(False), "p"))


def corrupt_facts(facts: DataFrame, modulo: int, kind: str = "interval", shift: int = 86_400_000_000) -> DataFrame:
    """Every modulo-th fact (by hash) with a wrong object, property or interval: stress data, not real errors."""
    pick = F.pmod(F.conv(F.substring(F.md5("fact_id"), 1, 8), 16, 10).cast("long"), F.lit(modulo)) == 0
    if kind == "object":
        return facts.withColumn("o", F.when(pick, F.concat("o", F.lit("~"))).otherwise(F.col("o")))
    if kind == "property":
        return facts.withColumn("p", F.when(pick, F.concat("p", F.lit("~"))).otherwise(F.col("p")))
    if kind != "interval":
        raise ValueError("kind is object, property or interval")
    moved = {c: F.when(pick, F.col(c) + shift).otherwise(F.col(c)) for c in ("te_lo", "te_hi")}
    return facts.withColumns(moved)


def rule_loss(base: DataFrame, pruned: DataFrame) -> DataFrame:
    """Rules of the base run, those that pruning lost, their share, and rules that only pruning has (none)."""
    lost = base.join(pruned, "cid", "left_anti").agg(F.count("*").alias("n_lost"))
    extra = pruned.join(base, "cid", "left_anti").agg(F.count("*").alias("n_extra"))
    n = base.agg(F.count("*").alias("n_base"))
    out = n.join(F.broadcast(lost), F.col("n_lost") <= F.col("n_base")).join(F.broadcast(extra), F.col("n_extra") >= 0)
    return out.withColumn("loss", F.round(F.try_divide(F.col("n_lost"), F.col("n_base")), 6))


def summary(rules: DataFrame, conflicts: DataFrame, name: str) -> DataFrame:
    r = rules.agg(F.count("*").alias("n_rules"))
    pair = F.struct(F.least("fact1", "fact2"), F.greatest("fact1", "fact2"))
    c = conflicts.agg(F.count("*").alias("n_conflicts"), F.count_distinct(pair).alias("n_pairs"))
    return r.join(F.broadcast(c), F.col("n_conflicts") >= 0).select(F.lit(name).alias("run"), "n_rules", "n_conflicts", "n_pairs")


def compare_runs(a: DataFrame, b: DataFrame) -> DataFrame:
    """Ratios of the second run's numbers to the first's."""
    left = a.select(F.col("run").alias("run_a"), F.col("n_rules").alias("rules_a"), F.col("n_conflicts").alias("conflicts_a"))
    right = b.select(F.col("run").alias("run_b"), F.col("n_rules").alias("rules_b"), F.col("n_conflicts").alias("conflicts_b"))
    both = left.join(F.broadcast(right), F.col("run_a") != F.col("run_b"))
    return both.withColumns({"rules_ratio": F.round(F.try_divide(F.col("rules_b"), F.col("rules_a")), 6), "conflicts_ratio": F.round(F.try_divide(F.col("conflicts_b"), F.col("conflicts_a")), 6)})


def planted_report(rules: DataFrame, planted: list[tuple[str, str, str]]) -> DataFrame:
    """Grade of mined rules by a catalogue of (head, p1, p2) that hold by construction: correct if listed, merit if coarse, else wrong."""
    spark = rules.sparkSession
    good = F.broadcast(spark.createDataFrame(planted, "head string, p1 string, p2 string").withColumn("listed", F.lit(True)))
    named = rules.join(good, ["head", "p1", "p2"], "left")
    grade = F.when(F.col("listed"), "C").when(F.col("confidence") <= 0.9, "M").otherwise("W")
    return named.withColumn("grade", grade).groupBy("grade").agg(F.count("*").alias("n"))


def ranking_metrics(ranked: DataFrame, ks: tuple[int, ...] = (1, 3, 10), rank: str = "rank") -> DataFrame:
    """Mean reciprocal rank and hits of the right answers, in percent."""
    gold = ranked.where("is_gold")
    hits = [F.round(100 * F.avg((F.col(rank) <= k).cast("double")), 6).alias(f"hits{k}") for k in ks]
    return gold.agg(F.count("*").alias("n_queries"), F.round(100 * F.avg(1.0 / F.col(rank)), 6).alias("mrr"), *hits)
