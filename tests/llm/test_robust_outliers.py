import math
import random
from collections import defaultdict

import numpy as np
import pytest

from tempo_rules.llm import quality_rules as qr

SF = "/root/testdata/sf0.001"


def features(r):
    w = max(r["n_words"], 1)
    return [math.log1p(r["n_words"]), math.log(max(r["word_chars"], 1) / w), *(math.sqrt(r[c] / w) for c in ("n_symbols", "n_dup_lines", "n_repeat_words"))]


def plain_mcd(x):
    """Starts, concentration steps and choice, straight over one group's rows."""
    n, d = x.shape
    floors = np.diag(np.square(qr.FLOORS))
    rank = lambda v, p: np.sort(v, axis=0)[max(0, math.ceil(p * n) - 1)]
    mid, scale = rank(x, 0.5), np.maximum((rank(x, 0.75) - rank(x, 0.25)) / 1.349, qr.FLOORS)
    z = (x - mid) / scale
    begin = [(mid, np.diag(scale**2)), (x.mean(0), np.cov(x.T, bias=True))]
    for y in (np.tanh(z), z / np.maximum(np.linalg.norm(z, axis=1), 1e-9)[:, None]):
        c = np.cov(y.T, bias=True)
        u = np.sqrt(np.maximum(np.diag(c), 1e-12))
        begin.append((mid, c / np.outer(u, u) * np.outer(scale, scale)))

    def step(mu, cov):
        diff = x - mu
        d2 = np.einsum("ij,jk,ik->i", diff, np.linalg.inv(cov), diff)
        near = x[d2 <= rank(d2, qr.COVER) * (1 + 1e-12)]
        return near.mean(0), np.cov(near.T, bias=True) * qr.CONSISTENT + floors

    det = lambda e: np.linalg.slogdet(e[1])[1]
    now = [(m, c + floors) for m, c in begin]
    for _ in range(qr.FIRST_STEPS):
        now = [step(*e) for e in now]
    done = []
    for e in sorted(now, key=det)[: qr.GO_ON]:
        for _ in range(qr.MOST_STEPS):
            new = step(*e)
            stop = det(e) - det(new) <= qr.SETTLED
            e = new
            if stop:
                break
        done.append(e)
    return min(done, key=det)


def test_distances_against_a_plain_estimate(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = [r for r in qr.judge_documents(docs).join(docs.select("doc_id", "lang", "source"), "doc_id").collect()]
    groups = defaultdict(list)
    for r in rows:
        if not r["base_failed"]:
            for key in (r["source"], None):
                groups[r["lang"], key].append(features(r))
    est = {k: (plain_mcd(np.array(v)), len(v)) for k, v in groups.items()}
    seen = 0
    for r in rows:
        if r["base_failed"]:
            assert r["distance"] is None and not r["kept"]
            continue
        ((mu, cov), n), (wide, _) = est[r["lang"], r["source"]], est[r["lang"], None]
        w = n / (n + qr.PRIOR_ROWS)
        diff = np.array(features(r)) - (w * mu + (1 - w) * wide[0])
        want = diff @ np.linalg.inv(w * cov + (1 - w) * wide[1]) @ diff
        assert r["distance"] == pytest.approx(want, rel=1e-6)
        assert r["kept"] == (want <= qr.CUT)
        seen += 1
    assert seen > 100


def test_least_determinant_beats_a_single_start():
    rnd = np.random.default_rng(3)
    x = np.vstack([rnd.normal(0, 1, (700, 5)), rnd.normal(9, 0.3, (200, 5))])
    mu, cov = plain_mcd(x)
    assert np.abs(mu).max() < 0.3 and (np.abs(np.diag(cov) - 1) < 0.9).all()


def test_constants():
    assert qr.PRIOR_ROWS == 200 and 50 < qr.CUT < 65 and 1.2 < qr.CONSISTENT < 1.6


def test_a_hot_source_and_clashing_columns(spark):
    rnd = random.Random(8)
    words = ["oak", "river", "stones", "cloud", "garden", "winterly", "road", "birds"]
    text = lambda: " ".join(rnd.choice(words) + str(rnd.randrange(50)) for _ in range(rnd.randrange(40, 90)))
    rows = [(i, text(), "en", "hot" if i % 3 else f"s{i % 7}", 1.0, 2) for i in range(300)] + [(900, "word " * 100_000, "en", "hot", 1.0, 2)]
    out = qr.judge_documents(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, distance double, start int")).collect()
    assert len(out) == 301 and sum(r["kept"] for r in out) >= 295 and not [r for r in out if r["doc_id"] == 900][0]["kept"]
