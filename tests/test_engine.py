import itertools
import json
import random

import pytest
from pyspark.sql import functions as F

from tempo_rules.functions import granule as g
from tempo_rules.functions.granule import Granule, Interval
from tempo_rules.functions.predicates import HEADS, PREDICATES, verdicts
from tempo_rules.functions.sql_surface import install, register_views
from tempo_rules.operators import certificates, complete, detect, evaluate, graph, joins, match, mine, prune, refine, score
from tempo_rules.operators.mine import MinerConfig, Pruning
from tempo_rules.plans import kg as K
from tempo_rules.plans import project
from tempo_rules.sources import readers

SF = "/root/testdata/sf0.001"
FACT = "fact_id string, s string, p string, o string, a string, b string"


def make(spark, rows):
    """Facts from (id, s, p, o, start label, end label)."""
    df = spark.createDataFrame(rows, FACT)
    i = Interval(g.granule(F.coalesce("a", F.lit(""))), g.granule(F.coalesce("b", F.lit(""))))
    return df.select("fact_id", "s", "p", "o", F.lit("res").alias("o_kind"), *i.named(), (F.col("a").isNotNull() | F.col("b").isNotNull()).alias("is_temporal"), F.lit("test").alias("src"))


def no_classes(spark, rows=()):
    return spark.createDataFrame(list(rows), "entity string, class string")


# an independent truth table: None is unknown
def k_or(*v):
    return True if True in v else (None if None in v else False)


def k_and(*v):
    return False if False in v else (None if None in v else True)


def k_not(v):
    return None if v is None else not v


def lt(a, b):
    return None if a is None or b is None else a < b


def eq(a, b):
    return None if a is None or b is None else a == b


def gt(a, b):
    return lt(b, a)


def le(a, b):
    return k_or(lt(a, b), eq(a, b))


def expected(head, i, j):
    (a, b), (c, d) = i, j
    prec = lambda a, b, c, d: k_or(lt(b, c), k_and(eq(b, c), k_or(k_not(eq(a, c)), k_not(eq(b, d)))))
    pos, neg = {
        "start": (eq(a, c), k_or(k_not(eq(a, c)), gt(a, d), lt(b, c))),
        "finish": (eq(b, d), k_or(k_not(eq(b, d)), lt(b, c), gt(a, d))),
        "before": (prec(a, b, c, d), k_or(gt(b, c), gt(b, d), gt(a, c), gt(a, d))),
        "disjoint": (k_or(prec(a, b, c, d), prec(c, d, a, b)), k_or(k_and(gt(b, c), k_or(le(b, d), le(a, c))), k_and(lt(a, d), k_or(le(d, b), le(c, a))))),
        "include": (k_and(le(a, c), le(d, b)), k_or(gt(a, c), gt(a, d), lt(b, d), lt(b, c))),
    }[head]
    return 1 if pos else -1 if neg else 0


INTERVALS = [(a, b) for a in (None, 1, 2, 3) for b in (None, 1, 2, 3) if a is None or b is None or a <= b]


def matrix(spark):
    rows = [(i, a, b, c, d) for i, ((a, b), (c, d)) in enumerate(itertools.product(INTERVALS, INTERVALS))]
    df = spark.createDataFrame(rows, "id int, a long, b long, c long, d long")
    year = lambda n: Granule(F.col(n) * 10, F.col(n) * 10 + 10, F.when(F.col(n).isNotNull(), F.lit(g.YEAR)))
    return rows, df, Interval(year("a"), year("b")), Interval(year("c"), year("d"))


def test_all_interval_pairs_against_a_truth_table(spark):
    rows, df, i, j = matrix(spark)
    assert len(rows) == 169
    got = {r["id"]: r for r in df.select("id", verdicts(i, j).alias("v")).collect()}
    totals = {h: [0, 0, 0] for h in HEADS}
    for n, a, b, c, d in rows:
        for h in HEADS:
            want = expected(h, (a, b), (c, d))
            assert got[n]["v"][h] == want, (h, a, b, c, d)
            totals[h][{1: 0, -1: 1, 0: 2}[want]] += 1
    assert totals == {"start": [29, 66, 74], "finish": [29, 66, 74], "before": [29, 65, 75], "disjoint": [58, 25, 86], "include": [15, 65, 89]}


def test_sql_functions_and_masks_agree(spark):
    install(spark)
    rows, df, i, j = matrix(spark)
    both = df.select("id", i.struct().alias("i"), j.struct().alias("j"), verdicts(i, j).alias("v"), verdicts(i, j, F.lit(0b00101)).alias("m"))
    for r in both.selectExpr("v", "m", *[f"t_{h}(i, j) AS {h}" for h in HEADS]).collect():
        assert all(r[h] == r["v"][h] for h in HEADS)
        assert r["m"]["start"] == r["v"]["start"] and r["m"]["before"] == r["v"]["before"] and r["m"]["include"] is None


def test_symmetric_heads(spark):
    _, df, i, j = matrix(spark)
    for h in ("start", "finish", "disjoint"):
        assert df.where(PREDICATES[h](i, j) != PREDICATES[h](j, i)).count() == 0


def test_time_table_and_labels(spark):
    rows = [("2021-12", "2022", True, False), ("2022-01", "2022", None, None), (None, "2022", None, None), ("2003-07", "2003-07", False, True), ("rubbish", "2022", None, None), ("2022-13", "2022", None, None)]
    df = spark.createDataFrame(rows, "a string, b string, l boolean, e boolean")
    a, b = g.granule(F.col("a")), g.granule(F.col("b"))
    for r in df.select(g.lt(a, b).alias("x"), g.eq(a, b).alias("y"), "l", "e").collect():
        assert (r["x"], r["y"]) == (r["l"], r["e"])
    strict = df.select("a", g.eq(a, b, "unknown").alias("y")).where("a = '2003-07'").first()
    assert strict["y"] is None


def career(spark, third="2012-12"):
    spans = [("1992-08", "2003-07"), ("2003-07", "2007-11"), ("2007-11" if third != "2012" else "2007", third), ("2009-01", "2009-07"), ("1996-09", "2009"), ("2013-01", "2013-05")]
    return make(spark, [(f"F{i}", "x", "member", f"o{i}", a, b) for i, (a, b) in enumerate(spans)])


def test_worked_example(spark):
    v = match.with_verdict(match.match_one_subject(K.temporal_edges(career(spark)), True), "disjoint")
    r = score.fact_scores(v).first()
    assert (r["n_pos"], r["n_neg"], r["n_unk"]) == (10, 4, 1) and r["confidence"] == pytest.approx(5 / 7)
    e = score.entity_scores(v).first()
    assert (e["n_pos"], e["n_neg"], e["confidence"]) == (0, 1, 0.0)
    other = match.with_verdict(match.match_one_subject(K.temporal_edges(career(spark, "2012")), True), "disjoint")
    r = score.fact_scores(other).first()
    assert (r["n_pos"], r["n_neg"], r["n_unk"]) == (9, 4, 2)


def test_entity_verdict_is_the_least(spark):
    rows = [("a", 1), ("a", 1), ("b", 1), ("b", -1), ("c", 1), ("c", 0), ("d", 0), ("d", -1)]
    got = {r["x"]: r["verdict"] for r in score.entity_verdicts(spark.createDataFrame(rows, "x string, verdict tinyint")).collect()}
    assert got == {"a": 1, "b": -1, "c": 0, "d": -1}


def test_linked_subjects(spark):
    rows = [("d1", "x", "died", "p1", "2000", "2000"), ("l1", "x", "killed_by", "y", None, None), ("d2", "y", "died", "p2", "1990", "1990"), ("d3", "u", "died", "p3", "1990", "1990"), ("l2", "u", "killed_by", "v", None, None), ("d4", "v", "died", "p4", "2000", "2000"), ("d5", "m", "died", "p5", "1990", "1990"), ("l3", "m", "killed_by", "n", None, None), ("d6", "n", "died", "p6", None, "")]
    kg = K.KnowledgeGraph(make(spark, rows), no_classes(spark))
    rules = detect.parse_rules(spark, [{"id": "R", "head": "before", "slots": ["died", "died"], "link": "killed_by"}])
    got = detect.detect_conflicts(kg, rules).collect()
    assert [(r["fact1"], r["fact2"], r["link_fact"]) for r in got] == [("d1", "d2", "l1")]


def test_survivors_equal_base_and_pruning_is_a_subset(spark):
    kg = project.graph(spark, SF, ("K1", "K2", "K3", "K8", "K11"))
    cfg = MinerConfig(min_support=5, patterns=("a",))
    cols = ["cid", "n_pos", "n_neg", "n_unk"]
    base = {tuple(r) for r in mine.mine_candidates(kg, cfg).select(cols).collect()}
    for pr in (Pruning(), Pruning(stage2=False), Pruning(undecided="protect"), Pruning(bound="hoeffding"), Pruning(alpha=1e9)):
        out = prune.mine_pruned(kg, cfg, pr)
        kept = {tuple(r) for r in out.candidates.select(cols).collect()}
        assert kept <= base and (pr.alpha < 1e9 or kept == base)
    fact = {tuple(r) for r in mine.mine_candidates(kg, MinerConfig(min_support=5, patterns=("a",), level="fact")).select(cols).collect()}
    sums = {r[0]: r[1] for r in fact}
    assert all(sums.get(cid, 0) >= pos for cid, pos, _, _ in base if not cid.startswith("never"))


def test_decisions_at_the_limits():
    cfg, pr = MinerConfig(min_support=100), Pruning()
    rule = ("before", "a_diff", None, None, "p", 1, "q", 1)
    assert prune.decide_rules({rule: [5, 46, 0]}, cfg, pr) == {rule}
    assert prune.decide_rules({rule: [24, 36, 0]}, cfg, pr) == set()
    assert prune.decide_rules({rule: [5, 45, 0]}, cfg, pr) == set()
    assert prune.decide_rules({rule: [0, 0, 51]}, cfg, pr) == {rule}
    counts = {rule: [10, 490, 0]}
    assert prune.decide_slots(counts, {rule}, cfg, pr) == {("p", 1), ("q", 1)}
    other = ("include", "a_diff", None, None, "p", 1, "r", 1)
    assert prune.decide_slots({**counts, other: [90, 10, 0]}, {rule}, cfg, pr) == {("q", 1)}
    assert prune.decide_slots(counts, set(), cfg, pr) == set()
    for bad in (lambda: Pruning(stage1=False), lambda: MinerConfig(accept_conf=0.5, refine_conf=0.9), lambda: MinerConfig(level="x"), lambda: Pruning(bound="x")):
        with pytest.raises(ValueError):
            bad()


def test_planted_rules_are_found(spark):
    cfg = MinerConfig(min_support=5, patterns=("a", "b"))
    rules = {(r["head"], r["p1"], r["p0"], r["p2"]): r["confidence"] for r in mine.mine_constraints(project.graph(spark, SF, ("K1", "K3", "K4", "K11")), cfg, refine=False).collect()}
    assert rules[("before", "said_system", None, "said_user")] == 1
    assert rules[("never", "ordered_on", None, "ordered_on")] == 1
    assert rules[("include", "active_as", "placed_order", "ordered_on")] == 1


def test_refinement_of_half_good_rules(spark):
    kg = project.graph(spark, SF, ("K8",))
    cfg = MinerConfig(min_support=5, patterns=("a",))
    found = mine.mine_constraints(kg, cfg).where("origin = 'refined' and head = 'disjoint'").collect()
    assert {(r["cy"], r["cz"]) for r in found} == {("browse", "browse"), ("browse", "deal"), ("deal", "deal")}
    text = [r["rule"] for r in mine.describe(mine.mine_constraints(kg, cfg)).collect()]
    assert any("y in browse, z in deal" in t for t in text)
    wide = spark.createDataFrame([("a", "*", "*"), ("b", "browse", "*"), ("c", "browse", "deal")], "cid string, cy string, cz string")
    full = wide.selectExpr("cid", "'h' head", "'a_same' pattern", "cast(null as string) p0", "cast(null as tinyint) d0", "'p' p1", "cast(1 as tinyint) d1", "'p' p2", "cast(1 as tinyint) d2", "'*' cx", "cy", "cz", "'*' cw")
    assert [r["cid"] for r in refine.most_general(full).collect()] == ["a"]


def test_certificates_equal_pairs(spark):
    e = K.temporal_edges(project.facts(spark, SF, ("K1", "K2", "K4", "K8", "K10", "K11")))
    pairs = match.ordered_pairs(match.match_one_subject(e, False))
    for h in ("start", "finish", "before", "include"):
        want = {tuple(r) for r in match.with_verdict(pairs, h).groupBy("p1", "d1", "p2", "d2", "x").agg(F.min("verdict")).collect()}
        assert {tuple(r) for r in certificates.entity_verdicts(e, h).collect()} == want
    assert certificates.hubs(e, 3).count() > 0


def test_degenerate_graphs(spark):
    empty = spark.createDataFrame([], K.SCHEMA)
    kg = K.KnowledgeGraph(empty, no_classes(spark))
    cfg = MinerConfig(min_support=1)
    assert mine.mine_constraints(kg, cfg).count() == 0 and mine.mine_constraints(kg, cfg, Pruning()).count() == 0
    rules = detect.parse_rules(spark, detect.HANDWRITTEN)
    assert detect.detect_conflicts(kg, rules).count() == 0 and detect.check_new_facts(kg, empty, rules).count() == 0
    assert detect.detect_conflicts(kg, rules.limit(0)).count() == 0
    odd = make(spark, [("a", "x", "p", "x", "2000", "2001"), ("b", "x", "p", "y", "2005", "2001"), ("c", "x", "p", "z", None, ""), ("a", "x", "p", "x", "2000", "2001"), ("d", "x", None, "w", "2000", "2000")])
    assert detect.self_conflicts(odd).select("fact_id").collect()[0][0] == "b"
    assert mine.mine_candidates(K.KnowledgeGraph(odd, no_classes(spark)), cfg).count() >= 0
    one = K.edges(K.edges(odd).where("d = -1").selectExpr("fact_id", "x s", "p", "y o", "o_kind", "ts_lo", "ts_hi", "ts_gran", "te_lo", "te_hi", "te_gran", "is_temporal", "src")).where("d = -1")
    assert one.select("x", "y").exceptAll(odd.select("s", "o")).count() == 0


def test_new_facts_and_reranking(spark):
    old = make(spark, [("o1", "u", "signup", "k1", "2024-01-05", "2024-01-05"), ("o2", "u", "view", "k2", "2024-01-06", "2024-01-06")])
    kg = K.KnowledgeGraph(old, no_classes(spark))
    rules = detect.parse_rules(spark, [{"id": "N", "head": "before", "slots": ["signup", "purchase"]}])
    new = make(spark, [("n1", "u", "purchase", "k9", "2024-01-01", "2024-01-01"), ("n2", "u", "purchase", "k9", "2024-02-01", "2024-02-01")])
    assert [r["new_fact"] for r in detect.check_new_facts(kg, new, rules).collect()] == ["n1"]
    pred = spark.createDataFrame([("q", "a", 1, False), ("q", "b", 2, True), ("q", "c", 3, False)], "qid string, cand_p string, rank int, is_gold boolean")
    flags = spark.createDataFrame([("q", "a"), ("q", "c")], "qid string, cand_p string")
    out = complete.rerank(pred, flags)
    assert [r["cand_p"] for r in out.orderBy("new_rank").collect()] == ["b", "a", "c"]
    assert evaluate.ranking_metrics(out).first()["mrr"] == 50 and evaluate.ranking_metrics(out, rank="new_rank").first()["mrr"] == 100
    same = complete.rerank(pred, flags.limit(0))
    assert same.where("rank <> new_rank").count() == 0


def test_grades_and_agreement(spark):
    rows = [("1", "CCW"), ("2", "CMW"), ("3", "WWM")]
    df = spark.createDataFrame([(i, str(k), x) for i, v in rows for k, x in enumerate(v)], "item string, rater string, grade string")
    assert {r["item"]: r["grade"] for r in evaluate.majority_grade(df).collect()} == {"1": "C", "2": "M", "3": "W"}
    agreed = spark.createDataFrame([(i, r, x) for i, x in (("1", "C"), ("2", "W")) for r in "abc"], "item string, rater string, grade string")
    assert evaluate.fleiss_kappa(agreed).first()["kappa"] == 1
    assert evaluate.fleiss_kappa(agreed.where("item = '1'")).first()["kappa"] is None


def test_components(spark):
    f = make(spark, [("1", "a", "p", "b", None, None), ("2", "b", "p", "c", None, None), ("3", "d", "p", "e", None, None)])
    seeds = spark.createDataFrame([("c",)], "entity string")
    assert {r["fact_id"] for r in graph.component_of(f, seeds).collect()} == {"1", "2"}
    assert {r["fact_id"] for r in graph.component_of(f, seeds, 0).collect()} == set()


def test_joins_on_time(spark):
    l = spark.createDataFrame([("k", 5), ("k", 1), ("m", 9)], "k string, t long")
    r = spark.createDataFrame([("k", 2, "x"), ("k", 5, "y"), ("m", 10, "z")], "k string, t long, v string")
    assert sorted(map(tuple, joins.asof_join(l, r, ["k"], "t", ["v"]).collect()), key=str) == [("k", 1, None), ("k", 5, "y"), ("m", 9, None)]
    a = spark.createDataFrame([(i, i * 3, i * 3 + 10) for i in range(30)], "id int, lo long, hi long").withColumn("k", F.lit(1))
    got = {(x["l_id"], x["r_id"]) for x in joins.overlap_join(a, a, ["k"], "lo", "hi", 7).collect()}
    assert got == {(i, j) for i in range(30) for j in range(30) if i * 3 < j * 3 + 10 and j * 3 < i * 3 + 10}
    assert joins.salted_join(l, r.withColumnRenamed("t", "t2"), ["k"], 4, "t").count() == 5


def test_readers(spark, tmp_path):
    (tmp_path / "q.tsv").write_text("x\tmember\tteam\t2003-07\t2007\nx\tborn\tcity\t1980-01-02\t\nbroken\n")
    q = readers.read_quads(spark, str(tmp_path / "q.tsv")).collect()
    assert {(r["p"], r["ts_gran"], r["te_gran"]) for r in q} == {("member", 2, 3), ("born", 1, None)}
    lines = [{"s": "x", "p": "won", "o": "cup", "qualifiers": {"point_in_time": "1999"}}, {"s": "x", "p": "led", "o": "y", "qualifiers": {"start_time": "2000-05"}}, {"s": "x", "p": "is", "o": "z"}]
    (tmp_path / "s.json").write_text("\n".join(map(json.dumps, lines)) + "\nnot json\n")
    s = {r["p"]: r for r in readers.read_statements(spark, str(tmp_path / "s.json")).collect()}
    assert s["won"]["ts_lo"] == s["won"]["te_lo"] and s["led"]["te_lo"] is None and not s["is"]["is_temporal"] and len(s) == 3
    (tmp_path / "n.nt").write_text('<http://e/x> <http://e/member> _:b1 .\n_:b1 <http://e/value> <http://e/team> .\n_:b1 <http://e/start_time> "2003-07" .\n<http://e/x> <http://e/name> "A \\"b\\"" .\n# note\n')
    n = {r["p"]: r for r in readers.read_ntriples(spark, str(tmp_path / "n.nt")).collect()}
    assert n["member"]["o"] == "http://e/team" and n["member"]["is_temporal"] and n["name"]["o_kind"] == "lit" and len(n) == 2
    readers.register_quads_source(spark)
    assert spark.read.format("quads").load(str(tmp_path / "q.tsv")).count() == 3
    readers.write_facts(readers.read_quads(spark, str(tmp_path / "q.tsv")), str(tmp_path / "facts"))
    assert spark.read.parquet(str(tmp_path / "facts")).where("p = 'born'").count() == 1
    rules = mine.mine_constraints(project.graph(spark, SF, ("K11",)), MinerConfig(min_support=5, patterns=("a",)))
    mine.save_constraints(rules, str(tmp_path / "rules"), "json")
    assert {tuple(r) for r in mine.load_constraints(spark, str(tmp_path / "rules"), "json").collect()} == {tuple(r) for r in rules.collect()}


def plan(df):
    return df._jdf.queryExecution().toString()


def test_plans(spark):
    f = project.facts(spark, SF, ("K4",))
    assert "ReadSchema: struct<c_custkey:bigint,c_mktsegment:string>" in plan(f.select("s", "o"))
    e = K.temporal_edges(project.facts(spark, SF, ("K1",)))
    text = plan(match.match_one_subject(e, True).groupBy("x").agg(F.count("*")))
    physical = text[text.index("== Physical Plan ==") :]
    assert "CartesianProduct" not in physical and "NestedLoop" not in physical and "Python" not in physical
    table = project.SMALL
    assert "Python" not in plan(mine.mine_candidates(project.graph(spark, SF, table), MinerConfig(min_support=5)))


def test_bucketed_edges_round_trip(spark):
    e = K.temporal_edges(project.facts(spark, SF, ("K1",)))
    readers.write_bucketed(e, "edges_by_subject", 4)
    assert spark.table("edges_by_subject").count() == e.count()
    assert "4" in {r["data_type"] for r in spark.sql("DESCRIBE EXTENDED edges_by_subject").collect() if r["col_name"] == "Num Buckets"}
    spark.sql("DROP TABLE edges_by_subject")


def test_views(spark):
    register_views(project.graph(spark, SF, ("K11",)))
    assert spark.sql("SELECT count(*) FROM facts JOIN edges USING (fact_id)").first()[0] > 0


def test_stream_late_and_repeated_facts(spark, tmp_path):
    """A fact behind the watermark misses the stream's windows; the batch pass over the same facts counts it."""
    from datetime import datetime

    from tempo_rules.streaming import facts as st

    day = lambda d: datetime(2024, 1, d, 12)
    parts = [[(1, day(1)), (2, day(2))], [(3, day(20))], [(5, day(21))], [(4, day(1)), (3, day(20))]]
    for i, rows in enumerate(parts):
        df = spark.createDataFrame([(k, t, 7, "view", 1.0, '{"k": 3}') for k, t in rows], "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string")
        df.coalesce(1).write.parquet(str(tmp_path / f"p{i}"))
        next((tmp_path / f"p{i}").glob("part-*")).rename(tmp_path / f"{i}.parquet")
    import os

    for i in range(4):
        os.utime(tmp_path / f"{i}.parquet", (1000 + i, 1000 + i))
    events = st.read_events(spark, str(tmp_path), "*.parquet", 1)
    closed = st.drain(st.rates(st.event_facts(events), delay="1 day"))
    assert sorted(r["n"] for r in closed.collect()) == [1, 1]
    once = st.drain(st.without_repeats(st.event_facts(st.read_events(spark, str(tmp_path), "*.parquet", 1)), "30 days"))
    assert sorted(r["fact_id"] for r in once.collect()) == ["K10:1", "K10:2", "K10:3", "K10:4", "K10:5"]
    batch = spark.read.parquet(*[str(tmp_path / f"{i}.parquet") for i in range(4)]).withColumn("at", F.col("ts").cast("timestamp"))
    assert st.event_facts(batch).select("fact_id").distinct().count() == 5


def test_entry(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() > 0


def test_mined_rules_do_not_depend_on_the_folder_name(spark, tmp_path):
    from tempo_rules import catalogue

    (tmp_path / "other").symlink_to(SF)
    rules = [sorted(map(str, catalogue.QUERIES["mine_base"](spark, d).collect())) for d in (SF, str(tmp_path / "other"))]
    assert rules[0] == rules[1]


def _temporal(spark, rows):
    """fact_id, s, p, o, t as instant facts."""
    df = spark.createDataFrame(rows, "fact_id string, s string, p string, o string, ts_lo long")
    at = F.col("ts_lo")
    return df.withColumns({"ts_hi": at + 1, "ts_gran": F.lit(0).cast("tinyint"), "te_lo": at, "te_hi": at + 1, "te_gran": F.lit(0).cast("tinyint"), "o_kind": F.lit("res"), "is_temporal": F.lit(True), "src": F.lit("test")})


def test_ranks_of_objects_without_listing_all_of_them(spark):
    rng = random.Random(5)
    rows = [(f"f{i}", f"s{rng.randrange(6)}", rng.choice("pq"), f"o{rng.randrange(25)}", i) for i in range(120)]
    train, test = rows[:90], rows[90:]
    got = {r["qid"]: r["rank"] for r in complete.frequency_ranker(_temporal(spark, train), _temporal(spark, test), "o").where("is_gold").collect()}
    late = {r["qid"]: r["rank"] for r in complete.recency_ranker(_temporal(spark, train), _temporal(spark, test), "o").where("is_gold").collect()}
    pool = {r[3] for r in train}
    for fid, s, p, o, at in test:
        by_count = sorted(pool, key=lambda c: (-sum(r[1:4] == (s, p, c) for r in train), -sum(r[1] == s and r[3] == c for r in train), -sum(r[3] == c for r in train), c))
        last = lambda c, q: max((r[4] for r in train if r[1] == s and r[3] == c and q(r) and r[4] < at), default=-1)  # noqa: B023, E731
        by_time = sorted(pool, key=lambda c: (-last(c, lambda r: r[2] == p), -last(c, lambda r: True), c))  # noqa: B023
        assert got.get(fid) == (by_count.index(o) + 1 if o in pool else None)
        assert late.get(fid) == (by_time.index(o) + 1 if o in pool else None)


def test_ranked_lists_of_another_system(spark, tmp_path):
    (tmp_path / "lists.tsv").write_text("a\tq\t0.5\na\tp\t0.9\na\tr\tnone\na\tq\t0.7\nzz\tp\t1\na\t\t3\n")
    lists = readers.read_ranked_lists(spark, str(tmp_path / "lists.tsv"))
    ranked = complete.external_ranking(_temporal(spark, [("a", "s", "q", "o", 3)]), lists).orderBy("rank").collect()
    assert [(r["cand_p"], r["rank"], r["is_gold"]) for r in ranked] == [("p", 1, False), ("q", 2, True), ("r", 3, False)]


def test_only_classes_with_the_support_are_refined(spark):
    edges = spark.createDataFrame([(f"x{i}", "p", 1, "y1" if i < 3 else "y2") for i in range(4)], "x string, p string, d int, y string")
    classes = spark.createDataFrame([("y1", "A"), ("y2", "B"), ("x0", "C"), ("x1", "C")], "entity string, class string")
    subjects, objects = refine.frequent_classes(edges, classes, 2)
    assert [r["class"] for r in subjects.collect()] == ["C"] and [r["class"] for r in objects.collect()] == ["A"]


def test_components_by_the_last_two_hops(spark):
    pairs = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (5, 3), (6, 7)]
    facts = _temporal(spark, [(f"f{i}", f"n{a}", "p", f"n{b}", i) for i, (a, b) in enumerate(pairs)])
    seeds = spark.createDataFrame([("n0",), ("n0",)], "entity string")
    ids = lambda hops: sorted(int(r["fact_id"][1:]) for r in graph.component_of(facts, seeds, hops).collect())
    assert ids(None) == [0, 1, 2, 3, 4, 5, 6] and ids(0) == [0] and ids(1) == [0, 1, 2, 3] and ids(2) == [0, 1, 2, 3, 4]


def test_mined_reranking_lays_facts_by_subject_once(spark):
    """After the facts are laid, no row leaves its task: neither facts nor candidates are shuffled again."""
    from tempo_rules import catalogue

    df = catalogue.QUERIES["rank_reranked_mined"](spark, SF)
    assert df.count() > 0 and "hashpartitioning" not in plan(df)


def test_reranking_by_subject_equals_ranker_flags_and_reranking(spark):
    rng = random.Random(7)
    rows = [(f"f{i}", f"s{rng.randrange(12)}", rng.choice("pqr"), f"o{rng.randrange(5)}", rng.randrange(6)) for i in range(160)]
    rows += [("f200", "alone", "p", "o1", 3)]
    facts = _temporal(spark, rows)
    held = F.col("fact_id").isin(*[f"f{i}" for i in range(0, 160, 4)], "f200")
    kinds = [("before", "p", "q"), ("before", "q", "q"), ("include", "r", "p"), ("disjoint", "r", "r"), ("start", "q", "r"), ("never", "p", "p")]
    for head, a, b in kinds:
        rules = detect.parse_rules(spark, [{"id": "R", "head": head, "slots": [a, b]}])
        train = facts.where(~held)
        ranked = complete.frequency_ranker(train, facts.where(held))
        apart = complete.rerank(ranked, complete.conflict_flags(K.KnowledgeGraph(train, no_classes(spark)), ranked, rules))
        names = complete.property_names(facts)
        fused = complete.rerank_by_subject(complete.laid_by_subject(facts, names, held), names, rules)
        cols = ["qid", "cand_p", "rank", "is_gold", "flag", "new_rank"]
        assert sorted(map(tuple, fused.select(cols).collect())) == sorted(map(tuple, apart.select(cols).collect())), head


def test_tick_scores_equal_pair_scores(spark):
    rng = random.Random(8)
    rows = [(f"f{i}", f"s{rng.randrange(30)}", rng.choice("pq"), f"o{rng.randrange(6)}", rng.randrange(5)) for i in range(240)]
    e = K.temporal_edges(_temporal(spark, rows))
    cols = ["head", "pattern", "p1", "d1", "p2", "d2", "n_pos", "n_neg", "n_unk"]
    got = score.score_ticks(e.withColumn("fact", F.col("fact_id")))
    assert sorted(map(tuple, got.select(cols).collect())) == sorted(map(tuple, score.score_one_subject(match.match_one_subject(e)).select(cols).collect()))


def test_facts_with_absent_times_are_mined_by_their_bounds(spark, tmp_path):
    """One order without a date: the other path takes over, and keeps every other fact."""
    from pathlib import Path

    from tempo_rules import catalogue

    for f in Path(SF).iterdir():
        (tmp_path / f.name).symlink_to(f)
    (tmp_path / "orders.parquet").unlink()
    o = spark.read.parquet(f"{SF}/orders.parquet")
    o.withColumn("o_orderdate", F.when(F.col("o_orderkey") != 3, F.col("o_orderdate"))).write.parquet(str(tmp_path / "orders.parquet"))
    n = [catalogue.QUERIES["rank_reranked_mined"](spark, d).count() for d in (SF, str(tmp_path))]
    assert n[0] == n[1] > 0


def test_mined_measures_keep_no_candidate_but_the_right_one(spark, tmp_path):
    """Only ranks of right answers are written between re-ranking and its measures."""
    from tempo_rules import catalogue
    from tempo_rules.queries import completion

    names = []
    kept = completion.written
    completion.written = lambda df, name="t", *a: names.append((name, tuple(df.columns))) or kept(df, name, *a)
    try:
        assert catalogue.QUERIES["ranking_metrics_mined"](spark, SF).count() == 2
    finally:
        completion.written = kept
    assert names == [("gold", ("is_gold", "rank", "new_rank"))]


@pytest.mark.parametrize("name", ["score_worked_example", "time_granule_table"])
def test_examples_read_a_given_table(spark, name, monkeypatch):
    from tempo_rules import catalogue
    from tempo_rules.queries import graphs

    seen, read = [], graphs.table
    monkeypatch.setattr(graphs, "table", lambda s, d, n: seen.append(n) or read(s, d, n))
    assert catalogue.QUERIES[name](spark, SF).count() > 0 and seen == ["orders"]
