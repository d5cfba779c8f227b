"""K-means on a bounded sample, assignment in one narrow pass, and splits of single clusters."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .oracle import uniform

#: Vectors that centroids are fitted on.
FIT_SAMPLE = 4096


def lloyd(x: np.ndarray, k: int, seed: int = 42, rounds: int = 25) -> np.ndarray:
    """Centroids of Lloyd's method, seeded far apart."""
    rng = np.random.default_rng(seed)
    centres = x[[int(rng.integers(len(x)))]]
    while len(centres) < min(k, len(x)):
        far = ((x[:, None, :] - centres[None]) ** 2).sum(axis=2).min(axis=1)
        total = far.sum()
        centres = np.vstack([centres, x[int(rng.choice(len(x), p=far / total)) if total > 0 else int(rng.integers(len(x)))]])
    for _ in range(rounds):
        label = nearest(x, centres)
        new = np.vstack([x[label == c].mean(axis=0) if (label == c).any() else centres[c] for c in range(len(centres))])
        if np.allclose(new, centres):
            break
        centres = new
    return centres


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres**2).sum(axis=1)[None, :] - 2 * x @ centres.T).argmin(axis=1)


def fit(features: DataFrame, k: int, seed: int = 42, n: int | None = None) -> np.ndarray:
    """Centroids from the vectors with the smallest hashes, at most ``FIT_SAMPLE`` of them."""
    n = features.count() if n is None else n
    rank = uniform(F.col("doc_id"), ":fit")
    pool = features.filter(rank < min(1.0, 2.0 * FIT_SAMPLE / max(1, n)))
    got = pool.orderBy(rank, "doc_id").limit(FIT_SAMPLE).select("doc_id", "emb").toPandas().sort_values("doc_id")
    return lloyd(np.stack(got["emb"].to_numpy()).astype(float), k, seed)


def assign(features: DataFrame, centres: np.ndarray) -> DataFrame:
    """``doc_id, cluster_id`` by the nearest centroid; centroids travel with the task."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            c = nearest(np.stack(p["emb"].to_numpy()).astype(float), centres) if len(p) else []
            yield pd.DataFrame({"doc_id": p["doc_id"], "cluster_id": [str(int(v)) for v in c]})

    return features.select("doc_id", "emb").mapInPandas(run, "doc_id long, cluster_id string")


def bisect(members: DataFrame, features: DataFrame, seed: int = 42) -> DataFrame:
    """Splits every cluster of ``query_id, cluster_id, doc_id`` in two by the nearer of two centroids.

    All clusters are fitted at once on bounded samples; a side is named by its parent and 0 or 1.
    """
    size = members.groupBy("query_id", "cluster_id").agg(F.count("*").alias("n"))
    joined = members.join(features.select("doc_id", "emb"), "doc_id").join(F.broadcast(size), ["query_id", "cluster_id"])
    pool = joined.filter(uniform(F.col("doc_id"), ":bisect") < F.least(F.lit(1.0), F.lit(1024.0) / F.col("n")))

    def two(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("doc_id")
        c = lloyd(np.stack(pdf["emb"].to_numpy()).astype(float), 2, seed)
        c = np.vstack([c, c])[:2]
        return pd.DataFrame({"query_id": pdf["query_id"].iloc[:1], "cluster_id": pdf["cluster_id"].iloc[:1], "c0": [c[0]], "c1": [c[1]]})

    centres = pool.groupBy("query_id", "cluster_id").applyInPandas(two, "query_id string, cluster_id string, c0 array<double>, c1 array<double>")
    d = "aggregate(zip_with(emb, {c}, (x, y) -> (x - y) * (x - y)), 0D, (a, v) -> a + v)"
    side = F.expr(f"CASE WHEN {d.format(c='c0')} <= {d.format(c='c1')} THEN '.0' ELSE '.1' END")
    return joined.join(F.broadcast(centres), ["query_id", "cluster_id"]).select("query_id", "doc_id", F.concat("cluster_id", side).alias("cluster_id"))
