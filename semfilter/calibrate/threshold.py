"""Thresholds on confidence: candidates, ranges, pool counts and the choice among them."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..config import Config
from . import bounds

METHODS = ("blend", "naive", "uniform_margin", "hoeffding", "range_bound", "smoothed_histogram", "smoothed_band")


def candidates(conf: np.ndarray, m: int = 200) -> np.ndarray:
    """Quantiles of the calibration scores, and 0, one half and 1."""
    q = np.quantile(conf, np.linspace(0, 1, m)) if len(conf) else np.empty(0)
    return np.unique(np.round(np.concatenate([q, [0.0, 0.5, 1.0]]), 9))


def equal_freq_edges(conf: np.ndarray, ranges: int) -> np.ndarray:
    """Lower edges of equally filled ranges of sorted scores; equal edges merge, so ties stay together."""
    n = len(conf)
    if not n:
        return np.empty(0)
    b = min(ranges, n)
    size = np.full(b, n // b)
    size[: n % b] += 1
    return np.unique(np.sort(conf)[np.concatenate([[0], np.cumsum(size)[:-1]])])


def edges_for(conf: np.ndarray, tau: float, cfg: Config) -> np.ndarray:
    """Lower edges of the ranges of one threshold: the first one starts at the threshold."""
    accepted = conf[conf >= tau]
    source = conf if cfg.binning == "global" else accepted
    edges = equal_freq_edges(source, cfg.ranges)
    edges = edges[edges > tau]
    if cfg.binning != "global" and len(edges) and len(accepted) and edges[0] == accepted.min():
        edges = edges[1:]
    return np.concatenate([[tau], edges])


def cut_points(conf: np.ndarray, cfg: Config) -> np.ndarray:
    """All thresholds and edges of one query, on which its pool is counted once."""
    taus = candidates(conf, cfg.n_candidates)
    return np.unique(np.concatenate([taus, *[edges_for(conf, t, cfg) for t in taus], np.arange(cfg.hist_ranges + 1) / cfg.hist_ranges]))


def pool_counts(pool: DataFrame, cuts: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Pool documents below the first cut, between cuts, and above the last, for every query at once.

    One narrow pass and one small aggregation, whatever the number of thresholds; from the counts any
    range of any threshold follows by subtraction. ``pool`` has ``query_id, conf``.
    """

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            for q, own in p.groupby("query_id"):
                at = np.searchsorted(cuts[q], np.round(own["conf"].to_numpy(), 9), side="right")
                hit, n = np.unique(at, return_counts=True)
                yield pd.DataFrame({"query_id": q, "at": hit, "n": n})

    got = pool.select("query_id", "conf").mapInPandas(run, "query_id string, at int, n long").groupBy("query_id", "at").sum("n").toPandas()
    out = {q: np.zeros(len(c) + 1, np.int64) for q, c in cuts.items()}
    for q, at, n in got.itertuples(index=False):
        out[q][at] = n
    return out


@dataclass(frozen=True)
class Choice:
    """A threshold (infinite: cascade everything), what is expected below and above it, and its ranges."""

    tau: float
    cascade: int
    expected_errors: float
    bins: tuple = ()


def at_least(cuts: np.ndarray, counts: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """Pool documents at or above each edge."""
    above = np.concatenate([np.cumsum(counts[::-1])[::-1], [0]])
    return above[np.searchsorted(cuts, edges, side="right")]


def rates(k: np.ndarray, n: np.ndarray, method: str, cfg: Config) -> np.ndarray:
    if method == "naive":
        return bounds.blended(k, n, 0.0, cfg.delta)
    if method in ("range_bound", "uniform_margin"):
        return bounds.blended(k, n, 1.0, cfg.delta)
    if method == "hoeffding":
        return np.array([bounds.hoeffding_upper(a, b, cfg.delta) for a, b in zip(k, n, strict=True)])
    if method == "smoothed_histogram":
        return bounds.smoothed(k, n, cfg.smooth_c)
    return bounds.blended(k, n, cfg.blend, cfg.delta)


def select_tau(conf: np.ndarray, wrong: np.ndarray, cuts: np.ndarray, counts: np.ndarray, n_all: int, cfg: Config, method: str = "blend") -> Choice:
    """The threshold that cascades fewest documents while expected errors stay within (1 - alpha) N.

    Errors above a threshold are pool counts times rates, range by range; they need not be monotone,
    so every candidate is looked at. None feasible: everything is cascaded.
    """
    conf = np.round(conf, 9)
    order = np.argsort(conf, kind="stable")
    conf, wrong = conf[order], wrong[order]
    errors = np.concatenate([[0], np.cumsum(wrong)])
    budget = (1 - cfg.alpha) * n_all + 1e-9
    total = int(counts.sum())
    best = Choice(float("inf"), total, 0.0)
    for tau in candidates(conf, cfg.n_candidates):
        if method in ("uniform_margin", "hoeffding"):
            edges = np.array([tau])
        elif method == "smoothed_histogram":
            grid = np.arange(cfg.hist_ranges) / cfg.hist_ranges
            edges = np.concatenate([[tau], grid[grid > tau]])
        else:
            edges = edges_for(conf, tau, cfg)
        at = np.searchsorted(conf, edges, side="left")
        ends = np.append(at[1:], len(conf))
        n, k = ends - at, errors[ends] - errors[at]
        up = at_least(cuts, counts, edges)
        pool = up - np.append(up[1:], 0)
        expected = float((pool * rates(k, n, method, cfg))[pool > 0].sum())
        if expected <= budget and total - int(up[0]) < best.cascade:
            best = Choice(float(tau), total - int(up[0]), expected, tuple(zip(edges.tolist(), n.tolist(), k.tolist(), pool.tolist(), strict=True)))
    return best


def select_band(prob: np.ndarray, y: np.ndarray, pool_prob_counts: np.ndarray, n_all: int, cfg: Config) -> tuple[float, float, int]:
    """Lower and upper cut on probability over equal ranges; what lies between is cascaded: (lo, hi, cascaded)."""
    g = cfg.hist_ranges
    at = np.minimum((prob * g).astype(int), g - 1)
    n, yes = np.bincount(at, minlength=g), np.bincount(at, weights=y, minlength=g)
    rate = (yes + cfg.smooth_c) / (n + 2 * cfg.smooth_c)
    low = np.concatenate([[0.0], np.cumsum(pool_prob_counts * rate)])
    high = np.concatenate([np.cumsum((pool_prob_counts * (1 - rate))[::-1])[::-1], [0.0]])
    seen = np.concatenate([[0], np.cumsum(pool_prob_counts)])
    best = (0.0, 1.0, int(seen[-1]))
    for i in range(g + 1):
        for j in range(i, g + 1):
            cost = int(seen[j] - seen[i])
            if cost < best[2] and low[i] + high[j] <= (1 - cfg.alpha) * n_all + 1e-9:
                best = (i / g, j / g, cost)
    return best
