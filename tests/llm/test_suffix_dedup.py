import hashlib
import random

import tempo_rules.llm.suffix_dedup as sd

SF = "/root/testdata/sf0.001"


def brute(texts):
    seen = {}
    for d, t in enumerate(texts):
        for i in range(len(t) - 199):
            seen[t[i : i + 200]] = seen.get(t[i : i + 200], 0) + 1
    out = []
    for t in texts:
        gone = bytearray(len(t))
        for i in range(len(t) - 199):
            if seen[t[i : i + 200]] > 1:
                gone[i : i + 200] = b"\1" * 200
        spans = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        kept = bytes(c for c, g in zip(t, gone) if not g)
        out.append((len(t), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return out


def check(spark, rows):
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, rid string")
    got = sorted(tuple(r) for r in sd.remove_repeats(df).collect())
    want = sorted((i, *b) for (i, _), b in zip(rows, brute([(t or "").encode() for _, t in rows])))
    assert got == want


def _rows():
    rnd = random.Random(5)
    word = lambda: "".join(rnd.choice("abcdeé") for _ in range(rnd.randrange(1, 7)))
    text = lambda n: " ".join(word() for _ in range(n))
    passages = [text(60) for _ in range(4)]
    rows = []
    for i in range(120):
        t = text(rnd.randrange(5, 120))
        for p in rnd.sample(passages, rnd.randrange(3)):
            a = rnd.randrange(40)
            t += p[a : a + rnd.randrange(150, 260)] + text(rnd.randrange(3))
        rows.append((i, t))
    rows += [(200, None), (201, ""), (202, rows[3][1]), (202, rows[3][1]), (203, "a" * 700), (204, "ab" * 400), (205, passages[0] * 3)]
    rows += [(206, "q" * 199), (207, "q" * 199), (208, "r" * 200), (209, "r" * 200), (210, "x" + "\0" * 300 + "y")]
    return rows


def test_small_cases_against_brute_force(spark):
    check(spark, _rows())


def test_hot_anchors_are_subdivided_and_give_the_same_answer(spark, monkeypatch):
    monkeypatch.setattr(sd, "HOT", 3)
    widths = []
    real = sd._halved
    monkeypatch.setattr(sd, "_halved", lambda w: (widths.append(w), real(w))[1])
    rnd = random.Random(8)
    unlike = lambda n: "".join(rnd.choice("uvwxyz ") for _ in range(n))
    passage = unlike(230)
    # a passage with other text around it everywhere: stretches at its borders all differ
    rows = _rows() + [(300 + i, unlike(rnd.randrange(90, 300)) + passage + unlike(rnd.randrange(90, 300))) for i in range(40)]
    check(spark, rows)
    assert widths == [13, 1]


def test_a_common_stretch_does_not_shuffle(spark, monkeypatch):
    monkeypatch.setattr(sd, "HOT_SHARE", 1000)
    rnd = random.Random(9)
    passage = "".join(rnd.choice("abcdefgh ") for _ in range(900))
    rows = [(i, f"text {i} {rnd.random()} {passage} {rnd.random()}") for i in range(1500)]
    got = {r["doc_id"]: r["n_removed"] for r in sd.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(got) == 1500 and all(900 <= n <= 914 for n in got.values())


def test_whole_table_against_brute_force(spark):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    check(spark, rows)


def test_empty_table(spark):
    assert sd.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).collect() == []
