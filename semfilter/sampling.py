"""Reproducible samples: every choice is a hash of ids, whatever the partitioning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .oracle import uniform


def hash_sample(df: DataFrame, by: list[str], n: int, tag: str, rate: float | None = None) -> DataFrame:
    """The n documents of each group with the smallest hash.

    ``rate`` (several times n over the group's size) filters by hash before the ranking, so that only
    a multiple of the sample is shuffled; groups that come out short need a larger rate.
    """
    u = uniform(F.col("doc_id"), ":", tag)
    pool = df.withColumn("_u", u)
    if rate is not None and rate < 1:
        pool = pool.filter(F.col("_u") < rate)
    return pool.withColumn("_r", F.row_number().over(W.partitionBy(*by).orderBy("_u", "doc_id"))).filter(F.col("_r") <= n).drop("_u", "_r")


def split_sample(pairs: DataFrame, train: float, cal: float, tag: str = "split") -> DataFrame:
    """Marks ``query_id, doc_id`` pairs as train, cal or none by disjoint intervals of one hash."""
    u = uniform(F.col("doc_id"), ":", F.col("query_id"), ":", tag)
    return pairs.withColumn("part", F.when(u < train, "train").when(u < train + cal, "cal"))


def stratified_sample(scores: DataFrame, frac: float, strata: int, tag: str = "strata") -> DataFrame:
    """A share of each query's documents, the same in every stratum of the score."""
    by_score = W.partitionBy("query_id").orderBy("prob", "doc_id")
    cut = scores.withColumn("stratum", F.ntile(strata).over(by_score))
    u = uniform(F.col("doc_id"), ":", F.col("query_id"), ":", tag)
    ranked = cut.withColumn("_r", F.row_number().over(W.partitionBy("query_id", "stratum").orderBy(u, "doc_id")))
    size = F.count("*").over(W.partitionBy("query_id", "stratum"))
    return ranked.withColumn("_n", size).filter(F.col("_r") <= F.ceil(F.round(F.lit(frac) * F.col("_n"), 9))).drop("_r", "_n")
