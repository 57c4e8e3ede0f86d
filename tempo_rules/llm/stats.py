"""Distribution functions that numpy lacks: beta and chi-square, vectorised."""

from __future__ import annotations

import math

import numpy as np

_lgamma = np.frompyfunc(math.lgamma, 1, 1)


def log_beta(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    a, b = np.asarray(a, np.float64), np.asarray(b, np.float64)
    return np.asarray(_lgamma(a) + _lgamma(b) - _lgamma(a + b), np.float64)


def _fraction(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The continued fraction of the incomplete beta integral, by Lentz's steps until every element settles."""
    tiny = 1e-300
    safe = lambda v: np.where(np.abs(v) < tiny, tiny, v)
    c, d = np.ones_like(x), 1 / safe(1 - (a + b) * x / (a + 1))
    h = d.copy()
    for m in range(1, 100_000):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d, c = 1 / safe(1 + term * d), safe(1 + term / c)
            h *= d * c
        if (np.abs(d * c - 1) < 1e-13).all():
            break
    return h


def beta_cdf(x: np.ndarray, a: np.ndarray, b: np.ndarray, logs: np.ndarray | None = None) -> np.ndarray:
    """Probability that a beta variable of these parameters is at most x."""
    x, a, b = (np.asarray(v, np.float64) for v in np.broadcast_arrays(x, a, b))
    logs = log_beta(a, b) if logs is None else logs
    flip = x > (a + 1) / (a + b + 2)
    y, p, q = np.where(flip, 1 - x, x), np.where(flip, b, a), np.where(flip, a, b)
    inside = np.clip(y, 1e-300, 1 - 1e-16)
    part = np.exp(p * np.log(inside) + q * np.log1p(-inside) - logs) / p * _fraction(inside, p, q)
    out = np.clip(np.where(flip, 1 - part, part), 0, 1)
    return np.where(x <= 0, 0.0, np.where(x >= 1, 1.0, out))


def beta_quantile(p: float, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The x below which a beta variable lies with probability p: Newton steps inside a bracket that shrinks."""
    a, b = (np.asarray(v, np.float64) for v in (a, b))
    logs = log_beta(a, b)
    lo, hi, x = np.zeros_like(a), np.ones_like(a), a / (a + b)
    for _ in range(200):
        f = beta_cdf(x, a, b, logs) - p
        lo, hi = np.where(f < 0, x, lo), np.where(f < 0, hi, x)
        inside = np.clip(x, 1e-300, 1 - 1e-16)
        slope = np.exp((a - 1) * np.log(inside) + (b - 1) * np.log1p(-inside) - logs)
        with np.errstate(all="ignore"):
            new = x - f / slope
        new = np.where(np.isfinite(new) & (new > lo) & (new < hi), new, (lo + hi) / 2)
        if not len(x) or np.abs(new - x).max() < 1e-12:
            return new
        x = new
    return x


def chi2_cdf(x: float, k: int) -> float:
    """Probability that a chi-square variable of k degrees of freedom is at most x."""
    if x <= 0:
        return 0.0
    a, h = k / 2, x / 2
    term = total = 1 / a
    n = a
    while term > total * 1e-17:
        n += 1
        term *= h / n
        total += term
    return min(1.0, total * math.exp(a * math.log(h) - h - math.lgamma(a)))


def chi2_tail(x: float, k: int) -> float:
    """Probability that a chi-square variable of an odd or even number k of degrees of freedom is above x, exact for tiny ones."""
    if x <= 0:
        return 1.0
    h = x / 2
    # steps of two degrees of freedom from 1 or 2 upwards
    if k % 2:
        total, a = math.erfc(math.sqrt(h)), 0.5
    else:
        total, a = math.exp(-h), 1.0
    while a < k / 2:
        total += math.exp(a * math.log(h) - h - math.lgamma(a + 1))
        a += 1
    return total


def chi2_above(tail: float, k: int) -> float:
    """The x above which a chi-square variable of k degrees of freedom lies with this probability."""
    lo, hi = 0.0, 1.0
    while chi2_tail(hi, k) > tail:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi2_tail(mid, k) > tail else (lo, mid)
    return (lo + hi) / 2
