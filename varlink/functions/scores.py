"""Match score and probability, loss, recalibration and sampling bound as column expressions.

A pair of datasets has the score ``D = |h_a - h_b|^2 + g_a + g_b`` and the match probability ``exp(-D)``. D is a *squared*
distance: the triangle inequality holds for its root only, so all pruning uses the root.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from .vectors import dot, sq_dist

#: Below this D the loss of an unmatched pair is held constant; it is infinite at 0.
D_MIN = 1e-7


def embedding_distance(a: Column, b: Column, estimator: str = "v", spread_a: Column | None = None, spread_b: Column | None = None) -> Column:
    """Squared distance of mean vectors; ``u`` takes off each side's sampling variance (``spread``)."""
    d = sq_dist(a, b)
    return d if estimator == "v" else d - spread_a - spread_b


def mean_spread(mean: Column, mean_sq_norm: Column, n: Column) -> Column:
    """Unbiased estimate of the variance of a mean vector: trace of the covariance over n."""
    return F.when(n > 1, (mean_sq_norm - dot(mean, mean)) / (n - 1)).otherwise(F.lit(0.0))


def match_score(ha: Column, hb: Column, ga: Column, gb: Column) -> Column:
    return sq_dist(ha, hb) + ga + gb


def match_probability(d: Column) -> Column:
    return F.exp(-d)


def pair_loss(d: Column, y: Column) -> Column:
    """Cross entropy of ``exp(-d)``; the unmatched side is computed without cancellation."""
    return F.when(y == 1, d).otherwise(-F.log(-F.expm1(-F.greatest(d, F.lit(D_MIN)))))


def loss_gradient(d: Column, y: Column) -> Column:
    """Slope of the loss in D: 1 for matches; for others it grows without bound as D falls to 0."""
    return F.when(y == 1, F.lit(1.0)).otherwise(-1 / F.expm1(F.greatest(d, F.lit(D_MIN))))


def repository_vector(h: Column, g: Column) -> Column:
    """``h`` and two more places; with :func:`query_vector` the squared distance is the score."""
    return F.concat(h, F.array(F.sqrt(g), F.lit(0.0)))


def query_vector(h: Column, g: Column) -> Column:
    return F.concat(h, F.array(F.lit(0.0), F.sqrt(g)))


def recalibrate_prior(p: Column, base_rate: Column | float, train_rate: float = 0.5) -> Column:
    """Odds scaled from the share of matches in training to that among random pairs."""
    b = base_rate if isinstance(base_rate, Column) else F.lit(float(base_rate))
    odds = p / (1 - p) * (b / (1 - b)) * ((1 - train_rate) / train_rate)
    return F.when(p >= 1, F.lit(1.0)).otherwise(odds / (1 + odds))


def recalibrate_pu(p: Column, label_rate: Column | float) -> Column:
    """Positive and unlabelled: only ``label_rate`` of the matches were annotated."""
    r = label_rate if isinstance(label_rate, Column) else F.lit(float(label_rate))
    return F.least(F.lit(1.0), p / r)


def combine_scores(p_value: Column, p_label: Column, w: float = 0.5) -> Column:
    """Weighted mean of the log-odds of value and label similarity, both kept off 0 and 1."""
    safe = lambda p: F.least(F.greatest(p, F.lit(1e-6)), F.lit(1 - 1e-6))
    odds = lambda p: F.log(safe(p) / (1 - safe(p)))
    return 1 / (1 + F.exp(-((1 - w) * odds(p_value) + w * odds(p_label))))


def deviation_bound(n: Column, eps: Column, b: Column) -> Column:
    """Bound on the chance that a distance from ``n`` sampled values is off by more than ``eps``; ``b`` bounds |h|^2."""
    return 4 * F.exp(-n * eps * eps / (32 * b * b))


def adjustment_bound(n: Column, eps: Column, b: Column) -> Column:
    """The same for one adjustment g with values in [0, b] (Hoeffding)."""
    return 2 * F.exp(-2 * n * eps * eps / (b * b))


def samples_needed(eps: float, delta: float, b: float) -> int:
    """The least n whose deviation bound is at most ``delta``."""
    return math.ceil(32 * b * b / (eps * eps) * math.log(4 / delta))
