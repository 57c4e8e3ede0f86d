import json

from pyspark.sql import functions as F

from tempo_rules.functions.python_surface import FactAtoms, brute_force_before, granule_label, kappa_by_aggregate
from tempo_rules.operators import detect, evaluate, match
from tempo_rules.plans import kg, project

SF = "/root/testdata/sf0.001"


def test_odd_labels(spark):
    rows = [("July 2003", "2003-07"), ("12 May 1999", "1999-05-12"), ("1990s?", "1990"), ("soon", None), (None, None)]
    df = spark.createDataFrame(rows, "a string, b string")
    assert df.where(~granule_label("a").eqNullSafe(F.col("b"))).count() == 0


def test_brute_force_agrees_with_the_plan(spark):
    e = kg.temporal_edges(project.facts(spark, SF, ("K10",)))
    want = {tuple(r) for r in brute_force_before(e, "signup", "purchase").collect()}
    pairs = match.with_verdict(match.ordered_pairs(match.match_one_subject(e, False)), "before").where("p1 = 'signup' and p2 = 'purchase'")
    assert {tuple(r) for r in pairs.groupBy("x").agg(F.min("verdict").alias("v")).collect()} == want


def test_agreement_cross_check(spark):
    rows = [(str(i), r, g) for i, grades in enumerate(("CCM", "WWW", "CMW", "CCC", "MMW")) for r, g in zip("abc", grades)]
    df = spark.createDataFrame(rows, "item string, rater string, grade string")
    assert kappa_by_aggregate(df).first()["kappa"] == evaluate.fleiss_kappa(df).first()["kappa"]


def test_rule_atoms(spark):
    spark.udtf.register("fact_atoms", FactAtoms)
    rule = next(r for r in detect.HANDWRITTEN if r["id"] == "H7")
    got = spark.sql("SELECT * FROM fact_atoms(:r)", {"r": json.dumps(rule)}).collect()
    assert [(r["property"], r["subject"], r["object"]) for r in got] == [("active_as", "x", "y"), ("placed_order", "x", "w"), ("ordered_on", "w", "z")]
