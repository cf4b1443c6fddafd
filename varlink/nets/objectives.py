"""Losses on the scores of triplets, and their slopes: D of (anchor, positive) and of (anchor, negative)."""

from __future__ import annotations

import numpy as np

D_MIN = 1e-7


def cross_entropy(dp: np.ndarray, dn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per triplet: loss, slope in dp, slope in dn."""
    n = np.maximum(dn, D_MIN)
    return dp - np.log(-np.expm1(-n)), np.ones_like(dp), -1 / np.expm1(np.minimum(n, 700))


def triplet(dp, dn, margin: float = 1.0):
    on = (dp - dn + margin > 0).astype(float)
    return on * (dp - dn + margin), on, -on


def contrastive(dp, dn, margin: float = 4.0):
    on = (dn < margin).astype(float)
    return dp + on * (margin - dn), np.ones_like(dp), -on


def margin(dp, dn, alpha: float = 0.5, beta: float = 2.0):
    p, n = (dp - beta + alpha > 0).astype(float), (beta - dn + alpha > 0).astype(float)
    return p * (dp - beta + alpha) + n * (beta - dn + alpha), p, -n


OBJECTIVES = {"xent": cross_entropy, "triplet": triplet, "contrastive": contrastive, "margin": margin}


def pick_negatives(d: np.ndarray, allowed: np.ndarray, dp: np.ndarray, sampler: str, rng: np.random.Generator) -> np.ndarray:
    """For each row of ``d`` (scores of an anchor to the candidates) the index of its negative.

    ``uniform``; ``semihard``: the closest one beyond the positive; ``distance_weighted``: rare distances preferred.
    Rows without an allowed candidate get -1.
    """
    out = np.full(len(d), -1)
    for i, (row, ok) in enumerate(zip(d, allowed, strict=True)):
        idx = np.flatnonzero(ok)
        if not len(idx):
            continue
        if sampler == "semihard":
            beyond = idx[row[idx] > dp[i]]
            out[i] = beyond[row[beyond].argmin()] if len(beyond) else idx[row[idx].argmax()]
        elif sampler == "distance_weighted":
            # inverse density of distances on a sphere falls with a power of the distance; a mild one, clipped
            w = 1 / np.clip(np.sqrt(row[idx]), 0.3, 3.0) ** 2
            out[i] = rng.choice(idx, p=w / w.sum())
        else:
            out[i] = rng.choice(idx)
    return out
