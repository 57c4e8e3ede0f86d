import math

import numpy as np
import pytest

from tempo_rules.llm import stats, url_filters


def simpson_beta(x, a, b, n=20_000):
    """Plain integration of the beta density, for parameters of at least 1."""
    t = np.linspace(0, x, n + 1)
    with np.errstate(divide="ignore"):
        d = np.exp((a - 1) * np.log(t) + (b - 1) * np.log1p(-t) - (math.lgamma(a) + math.lgamma(b) - math.lgamma(a + b)))
    d[0] = 0 if a > 1 else d[1]
    return float((d[0] + d[-1] + 4 * d[1:-1:2].sum() + 2 * d[2:-1:2].sum()) * x / n / 3)


def test_beta_and_chi_square_against_integration():
    for a, b in ((1.5, 2), (3, 7.25), (40, 3), (900, 1100)):
        for x in (0.05, 0.3, 0.44, 0.9):
            assert float(stats.beta_cdf(x, a, b)) == pytest.approx(simpson_beta(x, a, b), abs=1e-6)
        q = stats.beta_quantile(0.05, np.array([a]), np.array([b]))[0]
        assert float(stats.beta_cdf(q, a, b)) == pytest.approx(0.05, abs=1e-9)
    low = stats.beta_quantile(0.05, np.array([0.1, 1e6, 1e-3]), np.array([3.1, 2e6, 5.0]))
    assert (low >= 0).all() and low[1] == pytest.approx(1 / 3, abs=1e-3)
    for k in (1, 2, 5, 7, 10):
        assert stats.chi2_cdf(4.2, k) + stats.chi2_tail(4.2, k) == pytest.approx(1, abs=1e-12)
        assert stats.chi2_tail(stats.chi2_above(1e-10, k), k) == pytest.approx(1e-10, rel=1e-6)
    assert stats.chi2_above(0.05, 5) == pytest.approx(11.0705, abs=1e-3)


def plain_reputations(rows):
    """The whole shrinkage over dictionaries."""
    parts = lambda h: (h.split(".")[-1], ".".join(h.split(".")[-2:]))
    count = {}
    for h, bad in rows:
        n, k = count.get(h, (0, 0.0))
        count[h] = (n + (bad is not None), k + (bad or 0))
    names = {"suffix": lambda h: parts(h)[0], "domain": lambda h: parts(h)[1], "host": lambda h: h}
    total = [sum(v[i] for v in count.values()) for i in (0, 1)]
    mean = {"": (total[1] + 1) / (total[0] + 2)}
    up = lambda h: ""
    for level in ("suffix", "domain", "host"):
        groups, kids = {}, {}
        for h, (n, k) in count.items():
            key = names[level](h)
            a = groups.get(key, (0, 0, up(h)))
            groups[key] = (a[0] + n, a[1] + k, up(h))
        for key, (n, k, p) in groups.items():
            if n:
                kids.setdefault(p, []).append((n, k))
        new, post = {}, {}
        for key, (n, k, p) in groups.items():
            m0 = 10.0
            if p in kids:
                own, w = kids[p], mean[p] * (1 - mean[p])
                size = sum(x for x, _ in own)
                spread = sum(x * (y / x - mean[p]) ** 2 for x, y in own)
                rho = 0.1
                if len(own) > 1 and w > 0:
                    rho = (spread - (len(own) - 1) * w) / max((size - sum(x * x for x, _ in own) / size) * w, 1e-9)
                    rho = min(max(rho, 1e-4), 0.5)
                m0 = min(max(1 / rho - 1, 1.0), 1000.0)
            a, b = mean[p] * m0 + k, (1 - mean[p]) * m0 + n - k
            new[key], post[key] = a / (a + b), (a, b)
        mean, up = new, names[level]
    return {h: (mean[h], *post[h]) for h in count}


def test_reputations_against_plain_computation(spark):
    rnd = np.random.default_rng(5)
    rows = []
    for d in range(12):
        share = rnd.random()
        for h in range(rnd.integers(1, 6)):
            rows += [(f"h{h}.dom{d}.{'org' if d % 3 else 'net'}", int(rnd.random() < share)) for _ in range(rnd.integers(1, 12))]
    rows += [("x.dom1.org", None), ("alone.dom99.net", None), ("", 1), ("localhost", 0)]
    got = {r["host"]: r for r in url_filters.reputations(spark.createDataFrame(rows, "host string, bad int")).collect()}
    want = plain_reputations(rows)
    assert set(got) == set(want)
    for h, (mean, a, b) in want.items():
        assert got[h]["bad_share"] == pytest.approx(mean, rel=1e-9)
        assert float(stats.beta_cdf(got[h]["bad_bound"], a, b)) == pytest.approx(0.05, abs=1e-8) and got[h]["bad_bound"] >= 0


def test_bound_of_a_host_without_bad_pages_is_not_negative(spark):
    (r,) = url_filters.reputations(spark.createDataFrame([("a.b", 0)] * 3, "host string, bad int")).collect()
    assert 0 <= r["bad_bound"] < r["bad_share"]


def test_suffixes_by_rule_and_by_list(spark):
    df = spark.createDataFrame([("a.b.co.uk",), ("b.co.uk",), ("co.uk",), ("x.b.com",), ("b.github.io",), ("uk",), ("",)], "host string")
    get = lambda w: [tuple(r) for r in df.select(*url_filters.suffix_and_domain(df.host, w)).collect()]
    assert get(None) == [("co.uk", "b.co.uk"), ("co.uk", "b.co.uk"), ("co.uk", "co.uk"), ("com", "b.com"), ("io", "github.io"), ("uk", "uk"), ("", "")]
    assert get(("github.io",))[4] == ("github.io", "b.github.io")


def test_repeated_rows_nulls_and_clashing_columns(spark):
    pages = spark.createDataFrame([(1, "http://a.net/x", 1), (1, "http://a.net/x", 1), (None, "http://a.net/x", 2), (2, "http://b.com/" + "p" * 300_000, 3)], "page_id long, url string, verdict int")
    labels = spark.createDataFrame([(1, 0, 0), (1, 1, None), (None, 0, 1)], "doc_id long, quality int, toxic int")
    out = url_filters.judge_pages(pages, labels).collect()
    assert sorted(str(r["page_id"]) for r in out) == ["1", "1", "2", "None"] and all(r["verdict"] in ("allow", "block") for r in out)
    assert max(len(r["path"]) for r in out) == 300_001
