"""Small-sample statistics in numpy: survival functions, two-sample tests, kernels."""

from __future__ import annotations

import math

import numpy as np


def ks_survival(gap: float, n1: float, n2: float) -> float:
    """p of the Kolmogorov-Smirnov gap by the asymptotic series with the small-sample factor; 1 where it is unstable."""
    e = n1 * n2 / (n1 + n2)
    lam = (math.sqrt(e) + 0.12 + 0.11 / math.sqrt(e)) * gap
    if lam < 0.2:
        return 1.0
    j = np.arange(1, 101)
    return float(np.clip(2 * np.sum((-1.0) ** (j - 1) * np.exp(-2 * j * j * lam * lam)), 0, 1))


def chi2_survival_even(s: float, degrees: int) -> float:
    """P(chi-square > s) for an even number of degrees: a finite Poisson sum."""
    half, term, total = s / 2, 1.0, 0.0
    for m in range(degrees // 2):
        term = 1.0 if m == 0 else term * half / m
        total += term
    return float(min(1.0, math.exp(-half) * total)) if half < 700 else 0.0


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function (modified Lentz)."""
    tiny, c, d = 1e-300, 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    h = d
    for m in range(1, 400):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + num * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + num / c
            c = c if abs(c) > tiny else tiny
            h *= c * d
        if abs(c * d - 1) < 1e-13:
            break
    return h


def beta_inc(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    return front * _beta_fraction(a, b, x) / a if x < (a + 1) / (a + b + 2) else 1 - front * _beta_fraction(b, a, 1 - x) / b


def f_survival(f: float, d1: float, d2: float) -> float:
    return beta_inc(d2 / 2, d1 / 2, d2 / (d2 + d1 * f)) if f > 0 else 1.0


def gamma_survival(a: float, x: float) -> float:
    """Upper regularised incomplete gamma function, by series or continued fraction."""
    if x <= 0:
        return 1.0
    front = math.exp(-x + a * math.log(x) - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        for k in range(1, 2000):
            term *= x / (a + k)
            total += term
            if term < total * 1e-15:
                break
        return 1 - front * total
    b, tiny = x + 1 - a, 1e-300
    c, d = 1 / tiny, 1 / b
    h = d
    for k in range(1, 2000):
        num = -k * (k - a)
        b += 2
        d = 1 / (num * d + b or tiny)
        c = b + num / c or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return front * h


def chi2_survival(s: float, degrees: float) -> float:
    return gamma_survival(degrees / 2, s / 2)


# ------------------------------------------------------------------ tests of two samples


def median_bandwidth(x: np.ndarray, y: np.ndarray, pairs: int = 1000, seed: int = 3) -> float:
    """Median absolute difference of random pairs of the pooled values; 1 when it is 0."""
    pool, rng = np.concatenate([x, y]), np.random.default_rng(seed)
    if len(pool) < 2:
        return 1.0
    a, b = rng.integers(0, len(pool), pairs), rng.integers(0, len(pool) - 1, pairs)
    return float(np.median(np.abs(pool[a] - pool[b + (b >= a)]))) or 1.0


def rbf(d: np.ndarray, bandwidth: float) -> np.ndarray:
    return np.exp(-(d * d) / (2 * bandwidth * bandwidth))


def mmd_linear(x: np.ndarray, y: np.ndarray, bandwidth: float) -> float:
    """Mean over disjoint consecutive pairs; 0 for fewer than two values a side."""
    n = min(len(x), len(y)) // 2
    if not n:
        return 0.0
    a, b, c, d = x[: 2 * n : 2], x[1 : 2 * n : 2], y[: 2 * n : 2], y[1 : 2 * n : 2]
    return float(np.mean(rbf(a - b, bandwidth) + rbf(c - d, bandwidth) - rbf(a - d, bandwidth) - rbf(b - c, bandwidth)))


def mmd_quadratic(x: np.ndarray, y: np.ndarray, bandwidth: float, estimator: str = "v") -> float:
    """All pairs; ``v`` counts each value with itself, ``u`` does not."""
    kxx, kyy, kxy = (rbf(a[:, None] - b[None], bandwidth) for a, b in ((x, x), (y, y), (x, y)))
    if estimator == "v":
        return float(kxx.mean() + kyy.mean() - 2 * kxy.mean())
    n, m = len(x), len(y)
    own = lambda k, s: (k.sum() - s) / (s * (s - 1)) if s > 1 else 0.0
    return float(own(kxx, n) + own(kyy, m) - 2 * kxy.mean())


def cf_features(z: np.ndarray, freqs: np.ndarray) -> np.ndarray:
    """Smoothed sine and cosine of standardised values at the test frequencies: n x 2J."""
    w = np.exp(-(z * z) / 2)[:, None]
    return np.concatenate([w * np.sin(z[:, None] * freqs), w * np.cos(z[:, None] * freqs)], axis=1)


def smooth_cf(x: np.ndarray, y: np.ndarray, freqs: np.ndarray, ridge: float = 1e-5) -> float:
    """Normalised quadratic form of the mean feature difference of the two samples."""
    pool = np.concatenate([x, y])
    sd = pool.std() or 1.0
    fx, fy = cf_features((x - pool.mean()) / sd, freqs), cf_features((y - pool.mean()) / sd, freqs)
    diff = fx.mean(axis=0) - fy.mean(axis=0)
    cov = lambda f: np.atleast_2d(np.cov(f, rowvar=False)) if len(f) > 1 else np.zeros((f.shape[1],) * 2)
    sigma = cov(fx) / len(x) + cov(fy) / len(y) + ridge / max(1, min(len(x), len(y))) * np.eye(len(diff))
    return float(diff @ np.linalg.solve(sigma, diff))


def smooth_cf_moments(n1: float, mean1: np.ndarray, cross1: np.ndarray, n2: float, mean2: np.ndarray, cross2: np.ndarray, ridge: float = 1e-5) -> float:
    """The same from counts, means and centred sums of products of the features."""
    d, diff = len(mean1), mean1 - mean2
    cov = lambda n, c: c.reshape(d, d) / (n - 1) if n > 1 else np.zeros((d, d))
    sigma = cov(n1, cross1) / n1 + cov(n2, cross2) / n2 + ridge / max(1, min(n1, n2)) * np.eye(d)
    return float(diff @ np.linalg.solve(sigma, diff))


def hotelling(x: np.ndarray, y: np.ndarray, ridge: float = 1e-6, diag: bool = False) -> tuple[float, float]:
    """T-squared of two sets of vectors and its p; chi-square with a ridge where the covariance has no full rank."""
    n1, n2, d = len(x), len(y), x.shape[1]
    diff = x.mean(axis=0) - y.mean(axis=0)
    dof = max(1, n1 + n2 - 2)
    cx, cy = x - x.mean(axis=0), y - y.mean(axis=0)
    if diag:
        var = ((cx**2).sum(axis=0) + (cy**2).sum(axis=0)) / dof + ridge
        t2 = n1 * n2 / (n1 + n2) * float((diff * diff / var).sum())
        return t2, chi2_survival(t2, d)
    return hotelling_moments(n1, x.mean(axis=0), cx.T @ cx, n2, y.mean(axis=0), cy.T @ cy, ridge)


def hotelling_moments(n1: float, mean1: np.ndarray, cross1: np.ndarray, n2: float, mean2: np.ndarray, cross2: np.ndarray, ridge: float = 1e-6) -> tuple[float, float]:
    """The same from counts, means and centred sums of products."""
    d, diff, dof = len(mean1), mean1 - mean2, max(1, n1 + n2 - 2)
    s = (cross1 + cross2) / dof
    enough = n1 + n2 > d + 1
    scale = np.trace(s) / d or 1.0
    t2 = n1 * n2 / (n1 + n2) * float(diff @ np.linalg.solve(s + (ridge if enough else 0.1) * scale * np.eye(d), diff))
    if not enough:
        return t2, chi2_survival(t2, d)
    return t2, f_survival(t2 * (n1 + n2 - d - 1) / (d * (n1 + n2 - 2)), d, n1 + n2 - d - 1)


# ------------------------------------------------------------------ maps


def pca(x: np.ndarray, k: int) -> np.ndarray:
    c = x - x.mean(axis=0)
    u, s, _ = np.linalg.svd(c, full_matrices=False)
    return (u * s)[:, :k]


def tsne(x: np.ndarray, perplexity: float = 20.0, steps: int = 300, rate: float = 100.0, seed: int = 1) -> np.ndarray:
    """Two-dimensional neighbour embedding of up to about a thousand points."""
    n = len(x)
    d = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    p, target = np.zeros((n, n)), math.log(min(perplexity, max(2, (n - 1) / 3)))
    for i in range(n):
        low, high, beta = 0.0, np.inf, 1.0
        others = np.arange(n) != i
        for _ in range(50):
            e = np.exp(-(d[i, others] - d[i, others].min()) * beta)
            q = e / e.sum()
            h = -(q * np.log(np.maximum(q, 1e-12))).sum()
            if abs(h - target) < 1e-4:
                break
            low, high = (beta, high) if h > target else (low, beta)
            beta = beta * 2 if high == np.inf else (low + high) / 2
        p[i, others] = q
    p = np.maximum((p + p.T) / (2 * n), 1e-12)
    y = pca(x, 2) if x.shape[1] >= 2 else np.c_[x, np.zeros(n)]
    y = y / (y.std() or 1) * 1e-2 + np.random.default_rng(seed).normal(0, 1e-4, (n, 2))
    v = np.zeros_like(y)
    for step in range(steps):
        w = 1 / (1 + ((y[:, None] - y[None]) ** 2).sum(axis=2))
        np.fill_diagonal(w, 0)
        q = np.maximum(w / w.sum(), 1e-12)
        pull = ((p * (4 if step < steps // 4 else 1) - q) * w)[:, :, None]
        v = (0.5 if step < steps // 4 else 0.8) * v - rate * 4 * (pull * (y[:, None] - y[None])).sum(axis=1)
        y = y + v
        y -= y.mean(axis=0)
    return y
