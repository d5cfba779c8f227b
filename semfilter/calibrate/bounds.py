"""Error rates of score ranges: empirical, bounded, blended, smoothed."""

from __future__ import annotations

import math

import numpy as np


_KNOWN: dict[tuple[int, int, float], float] = {}


def _solve(k: int, n: int, delta: float) -> float:
    if n <= 0 or k >= n:
        return 1.0
    if k == 0:
        return 1.0 - delta ** (1.0 / n)
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) for i in range(k + 1)]
    lo, hi = k / n, 1.0
    for _ in range(60):
        u = (lo + hi) / 2
        a, b = math.log(u), math.log1p(-u)
        tail = sum(math.exp(c + i * a + (n - i) * b) for i, c in enumerate(logs))
        lo, hi = (u, hi) if tail > delta else (lo, u)
    return (lo + hi) / 2


def binom_upper(k: int, n: int, delta: float = 0.05) -> float:
    """Largest error rate that k errors among n do not refute at level delta (one-sided, exact)."""
    key = (int(k), int(n), float(delta))
    if key not in _KNOWN:
        _KNOWN[key] = _solve(*key)
    return _KNOWN[key]


def hoeffding_upper(k: int, n: int, delta: float = 0.05) -> float:
    """The same by Hoeffding's inequality: looser, closed form."""
    return 1.0 if n <= 0 else min(1.0, k / n + math.sqrt(math.log(1 / delta) / (2 * n)))


def blended(k: np.ndarray, n: np.ndarray, w: float, delta: float) -> np.ndarray:
    """(1 - w) * empirical + w * upper bound, range by range; a range without labels has rate 1."""
    upper = np.array([binom_upper(a, b, delta) for a, b in zip(k, n, strict=True)], float)
    emp = np.where(n > 0, k / np.maximum(n, 1), 1.0)
    return (1 - w) * emp + w * upper


def smoothed(k: np.ndarray, n: np.ndarray, c: float = 1.0) -> np.ndarray:
    """Rates with c added to both outcomes, so that empty ranges stand at one half."""
    return (k + c) / (n + 2 * c)
