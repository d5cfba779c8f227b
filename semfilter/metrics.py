"""Cost and accuracy measures over ledgers, predictions and runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

PURPOSES = ("vote", "train", "cal", "cascade", "pilot")


def oracle_calls(ledger: DataFrame) -> DataFrame:
    """Labels bought for each query, by purpose and in all."""
    counts = [F.count_if(F.col("purpose") == p).alias(f"n_{p}") for p in PURPOSES]
    return ledger.groupBy("query_id").agg(*counts, F.count("*").alias("n_oracle"), F.sum("tokens").alias("oracle_tokens"))


def accuracy(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of documents whose output equals the oracle's answer, and the confusion behind it."""
    j = pred.join(truth.select("query_id", "doc_id", "y"), ["query_id", "doc_id"])
    hit, yes, said = F.col("yhat") == F.col("y"), F.col("y") == 1, F.col("yhat") == 1
    out = j.groupBy("query_id").agg(F.count("*").alias("n"), F.avg(hit.cast("double")).alias("accuracy"), F.count_if(yes & said).alias("tp"), F.count_if(~yes & said).alias("fp"), F.count_if(yes & ~said).alias("fn"))
    f1 = F.when(2 * F.col("tp") + F.col("fp") + F.col("fn") > 0, 2.0 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).otherwise(1.0)
    return out.withColumn("f1", f1).withColumn("base_rate", (F.col("tp") + F.col("fn")) / F.col("n"))


def loss_sums(scored: DataFrame) -> DataFrame:
    """What the losses of ``proxy.nets`` are sums of, for each query of ``query_id, prob, p_star, y``.

    ``n`` and ``n_soft`` count documents and those with a soft label, ``soft`` and ``hard`` are summed cross-entropies, ``conf`` is summed
    confidence and ``wrong`` confidence times error. Documents stay where they are; a row a partition and query is shuffled.
    """
    p = F.least(F.greatest("prob", F.lit(1e-7)), F.lit(1 - 1e-7))
    conf = 2 * F.abs(F.col("prob") - 0.5)

    def bce(t):
        return F.sum(-t * F.log(p) - (1 - t) * F.log(1 - p))

    return scored.groupBy("query_id").agg(
        F.count("*").alias("n"), F.count("p_star").alias("n_soft"), bce(F.col("p_star")).alias("soft"), bce(F.col("y")).alias("hard"),
        F.sum(conf).alias("conf"), F.sum(conf * F.when(F.col("y") == 1, 1 - F.col("prob")).otherwise(F.col("prob"))).alias("wrong"),
    )


def summary(runs: DataFrame, *by: str) -> DataFrame:
    """Mean cost, mean calls, queries that met the target and summed shortfall, for each group of runs."""
    return runs.groupBy(*by).agg(
        F.count("*").alias("n_queries"), F.avg("e2e_s").alias("mean_e2e_s"), F.avg("n_oracle").alias("mean_calls"), F.sum("sla_hit").cast("long").alias("hits"),
        F.sum("sla_gap").alias("violation"), F.avg("accuracy").alias("mean_accuracy"), F.min("accuracy").alias("min_accuracy"),
    )


def envelope(runs: DataFrame) -> DataFrame:
    """Each run against the cheapest one of its query: rank of the query along the envelope, and the factor above it."""
    q = W.partitionBy("corpus", "query_id")
    best = F.min("e2e_s").over(q)
    out = runs.withColumn("envelope_s", best).withColumn("factor", F.col("e2e_s") / best)
    return out.withColumn("wins", (F.row_number().over(q.orderBy("e2e_s", "method")) == 1).cast("int"))


def speedup(runs: DataFrame, base: str) -> DataFrame:
    """Mean cost of ``base`` over that of each method, by corpus."""
    mean = runs.groupBy("corpus", "method").agg(F.avg("e2e_s").alias("m"))
    b = mean.filter(F.col("method") == base).select("corpus", F.col("m").alias("b"))
    return mean.join(F.broadcast(b), "corpus").select("corpus", "method", (F.col("b") / F.col("m")).alias("speedup"))
