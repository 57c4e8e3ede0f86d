import itertools
import random
import re
from collections import defaultdict
from fractions import Fraction

import pytest

from tempo_rules.llm.near_duplicates import join_texts, prefix_length

SF = "/root/testdata/sf0.01"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows):
    """doc index -> (class by least doc_id, links)."""
    sets = [frozenset(zip(*[WORD.findall(t or "")[k:] for k in range(5)])) for _, t in rows]
    solid = [bool(WORD.search(t or "")) for _, t in rows]
    near = defaultdict(set)
    holders = defaultdict(list)
    for i, s in enumerate(sets):
        for x in s:
            holders[x].append(i)
    same = defaultdict(list)
    for i, (_, t) in enumerate(rows):
        if solid[i]:
            same[t].append(i)
    for g in same.values():
        for a, b in itertools.combinations(g, 2):
            near[a].add(b)
            near[b].add(a)
    for i, s in enumerate(sets):
        common = defaultdict(int)
        for x in s:
            for j in holders[x]:
                if j > i:
                    common[j] += 1
        for j, n in common.items():
            if Fraction(n, len(s) + len(sets[j]) - n) >= Fraction(4, 5):
                near[i].add(j)
                near[j].add(i)
    root = list(range(len(rows)))
    for i in range(len(rows)):
        if root[i] != i:
            continue
        stack = [i]
        while stack:
            a = stack.pop()
            for b in near[a]:
                if root[b] > i and root[b] == b and b != i:
                    root[b] = i
                    stack.append(b)
    least = {}
    for i, r in enumerate(root):
        least[r] = min(least.get(r, rows[i][0]), rows[i][0])
    return sorted((rows[i][0], least[root[i]], len(near[i])) for i in range(len(rows)))


def test_prefix_follows_the_target():
    assert prefix_length(0.8, 24, 8, 0.9999) == 5
    assert prefix_length(0.8, 24, 8, 0.5) == 8
    with pytest.raises(ValueError):
        prefix_length(0.2, 1, 4, 0.99)


def test_whole_table_against_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    got = sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in join_texts(docs).collect())
    assert got == brute(rows)


def test_large_groups_and_odd_rows(spark):
    rnd = random.Random(3)
    base = [f"w{rnd.randrange(5000)}" for _ in range(120)]
    rows = []
    for i in range(600):
        w = list(base)
        for _ in range(rnd.randrange(4)):
            w[rnd.randrange(len(w))] = f"x{rnd.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    rows += [(1000, None), (1001, None), (1002, ""), (1003, " \n"), (1004, "one two"), (1005, "one two"), (1006, "one two three"), (1007, "y " * 60000)]
    rows += [(1008, "a b c d e f"), (1008, "a b c d e f")]
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, rid string")
    got = sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in join_texts(df).collect())
    assert got == brute(rows)


def test_empty_table(spark):
    assert join_texts(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_a_chain_of_texts_that_are_no_duplicates_is_never_gathered(spark, monkeypatch):
    """Neighbours share about two thirds of their windows: all are candidates, none is linked."""
    import tempo_rules.llm.near_duplicates as nd

    words = [f"c{i}" for i in range(3000 * 12 + 60)]
    rows = [(i, " ".join(words[12 * i : 12 * i + 64])) for i in range(3000)]
    most = []
    real = nd._verified

    def watched(groups, sets, name):
        most.append(groups.groupBy("g1", "g2").count().agg({"count": "max"}).first()[0] or 0)
        return real(groups, sets, name)

    monkeypatch.setattr(nd, "_verified", watched)
    out = join_texts(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(r["class_id"] == r["doc_id"] and r["n_links"] == 0 for r in out) and len(out) == 3000
    assert max(most) < 40


def test_prefixes_are_shortened_until_the_recall_is_met(spark, monkeypatch):
    import tempo_rules.llm.near_duplicates as nd

    levels = []
    real = nd._met_again
    monkeypatch.setattr(nd, "_met_again", lambda *a: (levels.append(a[2]), real(*a))[1])
    rnd = random.Random(5)
    rows = []
    for i in range(200):
        w = [f"w{rnd.randrange(10**6)}" for _ in range(400)]
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join([*w, "one"]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert all(r["class_id"] == r["doc_id"] // 2 * 2 and r["n_links"] == 1 for r in join_texts(df).collect())
    # links are far more alike than the threshold: long prefixes have the recall
    assert levels == [8]
    levels.clear()
    join_texts(spark.createDataFrame(rows[::2], "doc_id long, text string")).collect()
    # without a link, only the shortest ones are sure to have it
    assert levels == [5]


def test_links_that_long_prefixes_show_ask_for_shorter_ones(spark, monkeypatch):
    """Whatever the estimates say in between, the answer is that of brute force."""
    import tempo_rules.llm.near_duplicates as nd

    levels, turn = [], iter((0.0, 1.0, 0.0, 0.0, 0.0, 1.0, 0.0, 0.0))
    real = nd._met_again
    monkeypatch.setattr(nd, "_met_again", lambda *a: (levels.append(a[2:]), real(*a))[1])
    monkeypatch.setattr(nd, "_recall", lambda *a: next(turn))
    monkeypatch.setattr(nd, "_first_links", lambda met, sets: nd._verified(met.where("false").selectExpr("rid g1", "rid g2", "rid", "0 side", "cast(null as binary) mask"), sets, "none"))
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    got = sorted((r["doc_id"], r["class_id"], r["n_links"]) for r in join_texts(docs).collect())
    assert got == brute(rows) and levels == [(7, None), (5, 7)]


def test_recall_by_similarity(spark):
    """Pairs of planned similarity from 0.8 up, each alone: nearly none is missed in any band."""
    rnd = random.Random(6)
    rows, alike = [], []
    for i in range(600):
        w = [f"w{rnd.randrange(10**7)}" for _ in range(204)]
        v = list(w)
        for at in rnd.sample(range(5, 199), rnd.randrange(1, 5)):
            v[at] = f"x{rnd.randrange(10**7)}"
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(v))]
        a, b = ({tuple(t[k : k + 5]) for k in range(200)} for t in (w, v))
        alike.append(len(a & b) / len(a | b))
    out = {r["doc_id"]: r["class_id"] for r in join_texts(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for lo, hi in ((0.8, 0.85), (0.85, 0.9), (0.9, 0.95), (0.95, 1.0)):
        band = [out[2 * i] == out[2 * i + 1] for i, s in enumerate(alike) if lo <= s < hi]
        assert len(band) > 50 and sum(band) / len(band) >= 0.99
    assert not any(out[2 * i] == out[2 * i + 1] for i, s in enumerate(alike) if s < 0.8)
