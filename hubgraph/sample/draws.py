"""Draws on the driver or inside Arrow functions: sequential skips, alias tables, weighted reservoirs."""

from __future__ import annotations

import numpy as np


def skip_positions(n: int, total: int, rng: np.random.Generator) -> list[int]:
    """n sorted distinct positions of range(total) by sequential skips: each skip is drawn from its exact law."""
    out, at = [], 0
    left = total
    while n > 0:
        # P(skip >= s) is the product of (left - n - i) / (left - i); inverted by search.
        u, s, keep = rng.random(), 0, 1.0
        while left - s > n:
            keep *= (left - s - n) / (left - s)
            if keep <= u:
                break
            s += 1
        out.append(at + s)
        at += s + 1
        left -= s + 1
        n -= 1
    return out


def aes_score(u, w):
    """u ** (1 / w); the logarithm -ln(u) / w orders the same way in reverse and does not underflow."""
    return np.power(u, 1.0 / np.asarray(w, float))


def build_alias(weights) -> tuple[np.ndarray, np.ndarray]:
    """Thresholds and aliases for draws with replacement in constant time."""
    p = np.asarray(weights, float) * len(weights) / np.sum(weights)
    threshold, alias = np.ones(len(p)), np.arange(len(p))
    low, high = [i for i, x in enumerate(p) if x < 1], [i for i, x in enumerate(p) if x >= 1]
    while low and high:
        a, b = low.pop(), high.pop()
        threshold[a], alias[a] = p[a], b
        p[b] -= 1 - p[a]
        (low if p[b] < 1 else high).append(b)
    return threshold, alias


def alias_draw(threshold: np.ndarray, alias: np.ndarray, n: int, rng: np.random.Generator) -> np.ndarray:
    i = rng.integers(0, len(threshold), n)
    return np.where(rng.random(n) < threshold[i], i, alias[i])
