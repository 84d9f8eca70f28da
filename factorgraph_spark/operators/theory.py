"""Bounds and small laws that the experiments are held against."""

from __future__ import annotations

import math

import numpy as np


def over_partition_bound(p: float, sigma: float, base: float = 2.0) -> float:
    """Order of the pieces per worker that balance work with high probability, if bisections split it with deviation sigma (at most 1/2)."""
    if sigma >= 0.5:
        return math.inf
    return p ** (1 / math.log(1 / (sigma + 0.5), base))


def chain_bound(n: int, p: int, tau: int) -> tuple[float, float]:
    """Steps of a chain run: 2n/p * ceil(tau p / n), and the simpler bound 2n/p + 2 tau."""
    return 2 * n / p * math.ceil(tau * p / n), 2 * n / p + 2 * tau


def degree_amplification(d: int, eps: float) -> float:
    """Change of the belief in state 0 if d uniform binary messages all move by eps."""
    a, b = d * math.log(0.5 - eps), d * math.log(0.5 + eps)
    return 0.5 - 1 / (1 + math.exp(b - a))


def tau_eps(priors: np.ndarray, pair: np.ndarray, eps: float) -> int:
    """On a chain: the least radius at which every vertex's belief from its neighbourhood is within eps (L1) of that from the whole chain."""
    n, s = priors.shape

    def passed(m: np.ndarray) -> np.ndarray:
        x = m[:, None] + pair
        top = x.max(axis=0)
        out = top + np.log(np.exp(x - top).sum(axis=0))
        return out - out.max()

    def norm(x):
        p = np.exp(x - x.max())
        return p / p.sum()

    def beliefs(radius: int) -> np.ndarray:
        left, right = np.zeros((n, s)), np.zeros((n, s))
        for _ in range(min(radius, n)):
            new_l, new_r = np.zeros((n, s)), np.zeros((n, s))
            for k in range(1, n):
                new_l[k] = passed(priors[k - 1] + left[k - 1])
            for k in range(n - 1):
                new_r[k] = passed(priors[k + 1] + right[k + 1])
            left, right = new_l, new_r
        return np.array([norm(priors[k] + left[k] + right[k]) for k in range(n)])

    whole = beliefs(n)
    for radius in range(n + 1):
        if np.abs(beliefs(radius) - whole).sum(axis=1).max() <= eps:
            return radius
    return n
