"""Bayes error of documents and queries, the floor on cascade calls, and the compass."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def eta(p):
    """Chance that an oracle asked again would answer otherwise than the likelier class."""
    return F.least(p, 1 - p)


def query_ber(answers: DataFrame) -> DataFrame:
    """Mean Bayes error of each query."""
    return answers.groupBy("query_id").agg(F.avg(eta(F.col("p_star"))).alias("ber"))


def pilot_ber(ledger: DataFrame) -> DataFrame:
    """The same over any labelled sample, with its standard error; costs no call."""
    e = eta(F.col("p_star"))
    return ledger.groupBy("query_id").agg(F.count("*").alias("n"), F.avg(e).alias("ber"), (F.stddev_samp(e) / F.sqrt(F.count("*"))).alias("std_error"))


def prefix_within(values: DataFrame, weight: str, budget: str, keys: list[str]) -> DataFrame:
    """How many of the smallest ``weight`` of each group fit into its ``budget`` together.

    Equal weights are counted first; running sums go over those counts, in runs found by the weight's
    own range, so no task holds a whole large group. Inside the group of equal weights where the budget
    ends, the number that still fits is a division.
    """
    v = F.round(F.col(weight), 9)
    counted = values.groupBy(*keys, v.alias("v")).agg(F.count("*").alias("n"), F.first(budget).alias("b"))
    run = counted.withColumn("run", F.floor(F.col("v") * 2048))
    inner = W.partitionBy(*keys, "run").orderBy("v").rowsBetween(W.unboundedPreceding, -1)
    outer = W.partitionBy(*keys).orderBy("run").rowsBetween(W.unboundedPreceding, -1)
    totals = run.groupBy(*keys, "run").agg(F.sum(F.col("v") * F.col("n")).alias("t")).withColumn("before", F.coalesce(F.sum("t").over(outer), F.lit(0.0))).drop("t")
    placed = run.withColumn("inside", F.coalesce(F.sum(F.col("v") * F.col("n")).over(inner), F.lit(0.0))).join(totals, [*keys, "run"])
    left = F.col("b") + 1e-9 - F.col("before") - F.col("inside")
    fits = F.when(left < 0, 0).when(F.col("v") <= 0, F.col("n")).otherwise(F.least(F.col("n"), F.floor(left / F.col("v"))))
    return placed.groupBy(*keys).agg(F.sum("n").cast("long").alias("n_docs"), F.sum(fits).cast("long").alias("fit"))


def bayes_floor(answers: DataFrame, alphas: list[float]) -> DataFrame:
    """Calls that even a cascade knowing every probability must make: ``query_id, alpha, n_docs, floor_calls``.

    Documents are given away by rising Bayes error while its sum stays within (1 - alpha) N.
    """
    sizes = answers.groupBy("query_id").agg(F.count("*").alias("n_all"))
    wide = answers.select("query_id", eta(F.col("p_star")).alias("eta")).join(F.broadcast(sizes), "query_id")
    wide = wide.withColumn("alpha", F.explode(F.array(*[F.lit(float(a)) for a in alphas]))).withColumn("budget", (1 - F.col("alpha")) * F.col("n_all"))
    got = prefix_within(wide, "eta", "budget", ["query_id", "alpha"])
    return got.select("query_id", "alpha", "n_docs", (F.col("n_docs") - F.col("fit")).alias("floor_calls"))


def omniscient(scores: DataFrame, alphas: list[float]) -> DataFrame:
    """The best threshold for a fixed scorer if all answers were known: ``query_id, alpha, tau, cascade, errors``.

    ``scores`` has ``query_id, doc_id, conf, wrong``; documents with equal confidence go together.
    """
    by = W.partitionBy("query_id").orderBy(F.desc("conf"))
    tied = scores.groupBy("query_id", F.round("conf", 9).alias("conf")).agg(F.count("*").alias("n"), F.sum("wrong").alias("w"))
    run = tied.withColumn("acc", F.sum("n").over(by)).withColumn("err", F.sum("w").over(by)).withColumn("n_all", F.sum("n").over(W.partitionBy("query_id")))
    fit = run.withColumn("alpha", F.explode(F.array(*[F.lit(float(a)) for a in alphas]))).filter(F.col("err") <= F.round((1 - F.col("alpha")) * F.col("n_all"), 9))
    best = fit.groupBy("query_id", "alpha").agg(F.max(F.struct("acc", "conf", "err")).alias("m"), F.first("n_all").alias("n_all"))
    return best.select("query_id", "alpha", F.col("m.conf").alias("tau"), (F.col("n_all") - F.col("m.acc")).cast("long").alias("cascade"), F.col("m.err").cast("long").alias("errors"))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3, rounds: int = 50) -> tuple[float, float]:
    """Intercept and slope of P(y = 1) against x, lightly penalised so that separable points have a fit."""
    scale = max(float(np.std(x)), 1e-9)
    a = np.column_stack([np.ones(len(x)), (x - x.mean()) / scale])
    w = np.zeros(2)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-a @ w))
        h = a.T @ (a * (p * (1 - p))[:, None]) + ridge * np.eye(2)
        w = w + np.linalg.solve(h, a.T @ (y - p) - ridge * w)
    slope = float(w[1] / scale)
    return float(w[0] - slope * x.mean()), slope


def auc(score: np.ndarray, win: np.ndarray) -> float:
    """Chance that a winner scores above a loser, ties counting half."""
    s, w = np.asarray(score, float), np.asarray(win, bool)
    if w.all() or not w.any():
        return 0.5
    pos, neg = s[w][:, None], s[~w][None, :]
    return float(((pos > neg) + 0.5 * (pos == neg)).mean())


def compass(runs, by: str = "cluster_vote") -> dict[str, float]:
    """Logistic fit of where ``by`` wins against Bayes error: intercept, slope, crossover and AUC."""
    x, y = runs["ber"].to_numpy(float), runs["win"].to_numpy(float)
    intercept, slope = logistic(x, y)
    return {"intercept": intercept, "slope": slope, "crossover": -intercept / slope if slope else float("nan"), "auc": auc(-x, y)}
