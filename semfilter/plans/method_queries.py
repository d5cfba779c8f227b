"""Queries of the methods, measures and experiments, with independent SQL twins."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import bayes, clustering, metrics
from .. import features as feat
from ..calibrate import bounds
from ..calibrate import threshold as th
from ..cascades import methods as ms
from ..config import Config
from ..oracle import ORACLE_MS, PREBUILT_MS, Ledger, PlantedOracle, TableOracle, against_truth, prob_from_logprobs, uniform
from ..proxy import nets
from ..proxy import train as px
from ..sampling import hash_sample, split_sample, stratified_sample
from ..sources import catalogue as cat
from ..sources.tables import save, table, views
from .registry import key

FEW = ("Q01", "Q04", "Q07", "Q19")
#: Queries on whose scores calibration is exercised: none is trivially met.
HARD = ("Q04", "Q08", "Q15", "Q19")
ALPHAS = (0.70, 0.75, 0.80, 0.85, 0.90, 0.95)


def truth(queries=FEW, mode="argmax", prebuilt=False) -> str:
    return f"({cat.truth_sql(cat.Duck, queries, mode, prebuilt)})"


def answers(spark: SparkSession, sf: str, queries=FEW, mode="argmax") -> DataFrame:
    return PlantedOracle(spark, sf, queries, mode).answers()


def u(*parts: str) -> str:
    return cat.Duck.uniform("concat(" + ", ".join(f"CAST({p} AS VARCHAR)" for p in parts) + ")")


def bench(spark: SparkSession, sf: str, queries=FEW, name="documents", **changes) -> ms.Bench:
    b = ms.Bench.documents(spark, sf, queries, Config(**{k: v for k, v in changes.items() if k in ("label_mode", "emb_dim")}), name)
    return replace(b, cfg=replace(b.cfg, **changes))


# ---- oracle and labels -------------------------------------------------------------------------
for _q in cat.ALL:

    @key(f"oracle_planted_{_q.lower()}", f"SELECT doc_id, round(p_star, 6) AS p_star, y FROM {truth((_q,))} t")
    def _planted(spark, sf, q=_q):
        return answers(spark, sf, (q,)).select("doc_id", F.round("p_star", 6).alias("p_star"), "y")


@key("oracle_labels", f"SELECT query_id, doc_id, y FROM {truth()} t")
def oracle_labels(spark, sf):
    return answers(spark, sf).select("query_id", "doc_id", "y")


@key("oracle_draw", f"SELECT query_id, doc_id, y FROM {truth(FEW, 'draw')} t")
def oracle_draw(spark, sf):
    return answers(spark, sf, FEW, "draw").select("query_id", "doc_id", "y")


@key("oracle_soft", f"SELECT query_id, doc_id, round(p_star, 6) AS p_star FROM {truth()} t")
def oracle_soft(spark, sf):
    return answers(spark, sf).select("query_id", "doc_id", F.round("p_star", 6).alias("p_star"))


for _c in ("quality", "toxic"):

    @key(f"oracle_{_c}", f"SELECT doc_id, CAST({_c} AS INT) AS y, CASE WHEN {_c} = 1 THEN 0.98 ELSE 0.02 END::DOUBLE AS p_star FROM labels WHERE {_c} IS NOT NULL")
    def _table_oracle(spark, sf, c=_c):
        return TableOracle(table(spark, sf, "labels"), c, c).answers().select("doc_id", "y", "p_star")


@key("soft_from_logprob", f"SELECT doc_id, round(p_star, 6) AS p_star FROM {truth(('Q04',))} t")
def soft_from_logprob(spark, sf):
    a = answers(spark, sf, ("Q04",)).withColumn("yes", F.log(F.col("p_star") * 0.9)).withColumn("no", F.log((1 - F.col("p_star")) * 0.9))
    return a.select("doc_id", F.round(prob_from_logprobs(F.col("yes"), F.col("no")), 6).alias("p_star"))


_TRAIN, _CAL = f"{u('doc_id', chr(39) + ':train' + chr(39))} < 0.3", f"{u('doc_id', chr(39) + ':cal' + chr(39))} < 0.2"


@key("ledger_dedup", f"""SELECT purpose, count(*) AS n, CAST(sum(y) AS BIGINT) AS yes FROM (
    SELECT y, CASE WHEN {_TRAIN} THEN 'train' ELSE 'cal' END AS purpose FROM {truth(('Q04',))} t WHERE {_TRAIN} OR {_CAL}) GROUP BY purpose""")
def ledger_dedup(spark, sf):
    """A training sample asked for twice and a calibration sample that overlaps it: each label is paid once."""
    a = save(answers(spark, sf, ("Q04",)))
    led, train = Ledger(a), a.filter(uniform(F.col("doc_id"), ":train") < 0.3)
    led.request(train.unionByName(train), "train")
    led.request(a.filter((uniform(F.col("doc_id"), ":train") < 0.3) | (uniform(F.col("doc_id"), ":cal") < 0.2)), "cal")
    return led.rows.groupBy("purpose").agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("yes"))


@key("ledger_reuse", f"SELECT 'train' AS purpose, count(*) AS n, CAST(sum(y) AS BIGINT) AS yes FROM {truth(('Q04',))} t WHERE {_TRAIN}")
def ledger_reuse(spark, sf):
    a = save(answers(spark, sf, ("Q04",)))
    led = Ledger(a)
    led.request(a.filter(uniform(F.col("doc_id"), ":train") < 0.3), "vote")
    return led.reuse(["vote"], "train").groupBy("purpose").agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("yes"))


@key("oracle_truth_confusion", f"SELECT t.query_id, t.y, CAST(l.toxic AS INT) AS truth, count(*) AS n FROM {truth(('Q07',))} t JOIN labels l USING (doc_id) GROUP BY ALL")
def oracle_truth_confusion(spark, sf):
    return against_truth(answers(spark, sf, ("Q07",)), table(spark, sf, "labels"), "toxic")


# ---- fixed frames ------------------------------------------------------------------------------
# Runs of four methods on four queries of two corpora, and a ledger of three queries.
_RUNS = [
    (m, c, f"Q{q}", 0.9, acc, vote, train, cal, casc, vote + train + cal + casc, px_s, px_s + 0.132 * (vote + train + cal + casc), p2)
    for m, c, q, acc, vote, train, cal, casc, px_s, p2 in (
        ("cluster_vote", "A", 1, 0.97, 400, 0, 0, 0, 0.0, False), ("cluster_vote", "A", 2, 0.91, 900, 0, 0, 5200, 0.0, False),
        ("cluster_vote", "A", 3, 0.89, 800, 0, 0, 7000, 0.0, False), ("cluster_vote", "A", 4, 0.93, 400, 0, 0, 100, 0.0, False),
        ("prebuilt_cascade", "A", 1, 0.95, 0, 0, 500, 900, 165.0, False), ("prebuilt_cascade", "A", 2, 0.92, 0, 0, 500, 2100, 165.0, False),
        ("prebuilt_cascade", "A", 3, 0.90, 0, 0, 500, 4000, 165.0, False), ("prebuilt_cascade", "A", 4, 0.94, 0, 0, 500, 300, 165.0, False),
        ("hybrid_cascade", "A", 1, 0.93, 0, 700, 500, 200, 15.2, True), ("hybrid_cascade", "A", 2, 0.91, 0, 700, 500, 700, 15.2, True),
        ("hybrid_cascade", "A", 3, 0.85, 0, 700, 500, 1900, 15.2, True), ("hybrid_cascade", "A", 4, 0.92, 0, 700, 500, 90, 15.2, True),
        ("two_phase", "A", 1, 0.97, 400, 0, 0, 0, 0.0, False), ("two_phase", "A", 2, 0.91, 700, 0, 500, 800, 15.2, True),
        ("two_phase", "A", 3, 0.90, 700, 0, 500, 2000, 15.2, True), ("two_phase", "A", 4, 0.93, 400, 0, 0, 0, 0.0, False),
        ("cluster_vote", "G", 1, 0.92, 400, 0, 0, 300, 0.0, False), ("cluster_vote", "G", 2, 0.90, 900, 0, 0, 6200, 0.0, False),
        ("prebuilt_cascade", "G", 1, 0.96, 0, 0, 500, 800, 232.0, False), ("prebuilt_cascade", "G", 2, 0.91, 0, 0, 500, 1800, 232.0, False),
        ("hybrid_cascade", "G", 1, 0.89, 0, 700, 500, 300, 15.3, True), ("hybrid_cascade", "G", 2, 0.92, 0, 700, 500, 1200, 15.3, True),
        ("two_phase", "G", 1, 0.92, 400, 0, 0, 300, 0.0, False), ("two_phase", "G", 2, 0.90, 700, 0, 500, 1100, 15.2, True),
    )
]
_BER = {("A", "Q1"): 0.004, ("A", "Q2"): 0.03, ("A", "Q3"): 0.08, ("A", "Q4"): 0.01, ("G", "Q1"): 0.02, ("G", "Q2"): 0.06}
RUNS = "(SELECT * FROM (VALUES " + ", ".join(f"('{r[0]}', '{r[1]}', '{r[2]}', {r[3]}e0, {r[4]}e0, {r[5]}, {r[6]}, {r[7]}, {r[8]}, {r[9]}, {r[10]}e0, {r[11]:.6f}e0, {str(r[12]).lower()}, {_BER[r[1], r[2]]}e0)" for r in _RUNS) + ") AS r(method, corpus, query_id, alpha, accuracy, n_vote, n_train, n_cal, n_cascade, n_oracle, proxy_s, e2e_s, phase2, ber))"
_LEDGER = [(f"Q{q}", d, (d * q) % 2, round(0.1 * ((d * 3 + q) % 10) + 0.05, 2), 100 + 10 * d, ("vote", "train", "cal", "cascade")[(d + q) % 4]) for q in (1, 2, 3) for d in range(12)]
LEDGER = "(SELECT * FROM (VALUES " + ", ".join(f"('{a}', {b}, {c}, {d}e0, {e}, '{f}')" for a, b, c, d, e, f in _LEDGER) + ") AS l(query_id, doc_id, y, p_star, tokens, purpose))"


# The same two frames from the given tables: labels that are paid for, and what three methods cost and reach on each language's documents.
_BOUGHT = "SELECT '{c}' AS query_id, l.doc_id, CAST(l.{c} AS INT) AS y, CASE WHEN l.{c} = 1 THEN 0.98e0 ELSE 0.02e0 END AS p_star, d.n_chars AS tokens, CASE l.doc_id % 4 WHEN 0 THEN 'vote' WHEN 1 THEN 'train' WHEN 2 THEN 'cal' ELSE 'cascade' END AS purpose FROM labels l JOIN documents d ON l.doc_id = d.doc_id WHERE l.{c} IS NOT NULL"
TABLE_LEDGER = f"({_BOUGHT.format(c='quality')} UNION ALL {_BOUGHT.format(c='toxic')})"
_LIVE = ("Q01", "Q04", "Q07", "Q08", "Q15", "Q19")
TABLE_RUNS = f"""(WITH g AS (SELECT d.lang AS corpus, t.query_id, count(*) AS n, round(avg(least(t.p_star, 1 - t.p_star)), 9) AS ber, greatest(avg(t.y), 1 - avg(t.y)) AS agreement,
    count(*) FILTER (WHERE t.conf < 0.4) AS unsure, count(*) FILTER (WHERE t.conf < 0.2) AS doubted, count(*) FILTER (WHERE t.conf < 0.4 OR t.y = t.yhat) AS good, count(*) FILTER (WHERE t.conf < 0.2 OR t.y = t.yhat) AS fair
    FROM (SELECT *, round(2 * abs(prob - 0.5), 9) AS conf, CASE WHEN prob >= 0.5 THEN 1 ELSE 0 END AS yhat FROM {truth(_LIVE, prebuilt=True)} s) t JOIN documents d ON d.doc_id = t.doc_id GROUP BY 1, 2)
    SELECT corpus, query_id, ber, 'cluster_vote' AS method, CASE WHEN agreement >= 0.9 THEN agreement ELSE 1e0 END AS accuracy, 0.132e0 * CASE WHEN agreement >= 0.9 THEN least(n, 20) ELSE n END AS e2e_s FROM g
    UNION ALL SELECT corpus, query_id, ber, 'prebuilt_cascade', good / n, 0.0165e0 * n + 0.132e0 * unsure FROM g
    UNION ALL SELECT corpus, query_id, ber, 'hybrid_cascade', fair / n, 0.00152e0 * n + 0.132e0 * (n * 3 // 25 + doubted) FROM g)"""


def table_ledger(spark: SparkSession, sf: str) -> DataFrame:
    views(spark, sf, "labels", "documents")
    return spark.sql(f"SELECT * FROM {TABLE_LEDGER}")


def table_runs(spark: SparkSession, sf: str) -> DataFrame:
    """Voting pays 20 calls where a language agrees and all of them elsewhere; the cascades pay for documents below a fixed confidence."""
    a = answers(spark, sf, _LIVE).join(table(spark, sf, "documents").select("doc_id", F.col("lang").alias("corpus")), "doc_id")
    conf, hit = F.round(2 * F.abs(F.col("prob") - 0.5), 9), F.col("y") == (F.col("prob") >= 0.5).cast("int")
    g = a.groupBy("corpus", "query_id").agg(
        F.count("*").alias("n"), F.round(F.avg(bayes.eta(F.col("p_star"))), 9).alias("ber"), F.greatest(F.avg("y"), 1 - F.avg("y")).alias("agreement"),
        F.count_if(conf < 0.4).alias("unsure"), F.count_if(conf < 0.2).alias("doubted"), F.count_if((conf < 0.4) | hit).alias("good"), F.count_if((conf < 0.2) | hit).alias("fair"),
    )
    agree, n = F.col("agreement") >= 0.9, F.col("n")
    labels = n - n % 25  # 12 % of each whole 25, and below of what is left
    cost = {
        "cluster_vote": (F.when(agree, F.col("agreement")).otherwise(1.0), F.when(agree, F.least(n, F.lit(20))).otherwise(n), 0.0), "prebuilt_cascade": (F.col("good") / n, F.col("unsure"), 0.0165),
        "hybrid_cascade": (F.col("fair") / n, labels / 25 * 3 + F.floor(n % 25 * 3 / 25) + F.col("doubted"), 0.00152),
    }
    rows = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), acc.alias("accuracy"), calls.cast("long").alias("n_oracle"), (n * px_s + 0.132 * calls.cast("long")).alias("e2e_s")) for m, (acc, calls, px_s) in cost.items()]))
    return g.select("corpus", "query_id", "ber", F.lit(0.9).alias("alpha"), rows.alias("r")).select("corpus", "query_id", "ber", "alpha", "r.*").selectExpr("*", "CASE WHEN accuracy >= alpha THEN 1 ELSE 0 END AS sla_hit", "greatest(0e0, alpha - accuracy) AS sla_gap")


def runs(spark: SparkSession) -> DataFrame:
    return spark.sql(f"SELECT *, CASE WHEN accuracy >= alpha THEN 1 ELSE 0 END AS sla_hit, greatest(0e0, alpha - accuracy) AS sla_gap FROM {RUNS}")


# ---- cost and accuracy -------------------------------------------------------------------------
@key("cost_e2e", f"SELECT method, corpus, query_id, round(proxy_s + 0.132 * (n_vote + n_train + n_cal + n_cascade), 6)::DOUBLE AS e2e_s FROM {RUNS}")
def cost_e2e(spark, sf):
    return runs(spark).select("method", "corpus", "query_id", F.round("e2e_s", 6).alias("e2e_s"))


@key("cost_oracle_calls", f"SELECT query_id, count(*) AS n_oracle, CAST(sum(tokens) AS BIGINT) AS oracle_tokens FROM {LEDGER} GROUP BY 1")
def cost_oracle_calls(spark, sf):
    return metrics.oracle_calls(spark.sql(f"SELECT * FROM {LEDGER}")).select("query_id", "n_oracle", F.col("oracle_tokens").cast("long").alias("oracle_tokens"))


@key("cost_cascade_calls", f"SELECT query_id, count(*) AS n_cascade FROM {LEDGER} WHERE purpose = 'cascade' GROUP BY 1")
def cost_cascade_calls(spark, sf):
    return metrics.oracle_calls(spark.sql(f"SELECT * FROM {LEDGER}")).select("query_id", "n_cascade")


@key("cost_segments", f"""SELECT query_id, {', '.join(f"count(*) FILTER (WHERE purpose = '{p}') AS {p}" for p in ('vote', 'train', 'cal', 'cascade'))} FROM {LEDGER} GROUP BY 1""")
def cost_segments(spark, sf):
    wide = spark.sql(f"SELECT * FROM {LEDGER}").groupBy("query_id").pivot("purpose", ["vote", "train", "cal", "cascade"]).count()
    return wide.na.fill(0)


@key("cost_latency_model", f"SELECT query_id, round(avg(tokens * {ORACLE_MS} / 1000), 6)::DOUBLE AS t_llm FROM {LEDGER} GROUP BY 1")
def cost_latency_model(spark, sf):
    return spark.sql(f"SELECT * FROM {LEDGER}").groupBy("query_id").agg(F.round(F.avg(F.col("tokens") * ORACLE_MS / 1000), 6).alias("t_llm"))


_WORDS = "len(list_filter(string_split({}, ' '), lambda x: x <> ''))"


@key("cost_tokens", f"SELECT CAST(sum({_WORDS.format('text')}) AS BIGINT) AS tokens, count(*) AS n FROM documents")
def cost_tokens(spark, sf):
    return table(spark, sf, "documents").agg(F.sum(F.size(F.filter(F.split("text", " "), lambda x: x != ""))).alias("tokens"), F.count("*").alias("n"))


@key("cost_exhaustive", f"SELECT count(*) AS n, round(sum({_WORDS.format('text')}) * {ORACLE_MS} / 1000, 3)::DOUBLE AS seconds FROM documents")
def cost_exhaustive(spark, sf):
    return table(spark, sf, "documents").agg(F.count("*").alias("n"), F.round(F.sum(F.size(F.filter(F.split("text", " "), lambda x: x != ""))) * ORACLE_MS / 1000, 3).alias("seconds"))


_CORPORA = f"""SELECT 'documents' AS corpus, text FROM documents UNION ALL SELECT 'conversations', text FROM conversations
    UNION ALL SELECT 'pages', trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&[a-zA-Z#0-9]+;', ' ', 'g'), '\\s+', ' ', 'g')) FROM pages"""


@key("cost_by_corpus", f"SELECT corpus, count(*) AS n, round(avg({_WORDS.format('text')}), 3)::DOUBLE AS mean_tokens, round(avg({_WORDS.format('text')}) * {ORACLE_MS} / 1000, 6)::DOUBLE AS t_llm FROM ({_CORPORA}) GROUP BY 1")
def cost_by_corpus(spark, sf):
    from ..sources.tables import strip_html

    texts = [table(spark, sf, "documents").select(F.lit("documents").alias("corpus"), "text"), table(spark, sf, "conversations").select(F.lit("conversations"), "text"), table(spark, sf, "pages").select(F.lit("pages"), strip_html(F.col("html")))]
    every = texts[0].union(texts[1]).union(texts[2])
    n = F.size(F.filter(F.split("text", " "), lambda x: x != ""))
    return every.groupBy("corpus").agg(F.count("*").alias("n"), F.round(F.avg(n), 3).alias("mean_tokens"), F.round(F.avg(n) * ORACLE_MS / 1000, 6).alias("t_llm"))


_PRED = f"SELECT query_id, doc_id, y, CASE WHEN prob >= 0.5 THEN 1 ELSE 0 END AS yhat FROM {truth(FEW, prebuilt=True)} t"


@key("acc_corpus", f"SELECT query_id, round(avg(CASE WHEN y = yhat THEN 1.0 ELSE 0.0 END), 6)::DOUBLE AS accuracy FROM ({_PRED}) GROUP BY 1")
def acc_corpus(spark, sf):
    b = bench(spark, sf)
    return metrics.accuracy(ms.prebuilt_scores(b).select("query_id", "doc_id", "yhat"), b.answers).select("query_id", F.round("accuracy", 6).alias("accuracy"))


@key("acc_confusion", f"""SELECT query_id, count(*) FILTER (WHERE y = 1 AND yhat = 1) AS tp, count(*) FILTER (WHERE y = 0 AND yhat = 1) AS fp, count(*) FILTER (WHERE y = 1 AND yhat = 0) AS fn,
    round(avg(y), 6)::DOUBLE AS base_rate, round(coalesce(2.0 * count(*) FILTER (WHERE y = 1 AND yhat = 1) / nullif(sum(y) + sum(yhat), 0), 1), 6)::DOUBLE AS f1 FROM ({_PRED}) GROUP BY 1""")
def acc_confusion(spark, sf):
    b = bench(spark, sf)
    m = metrics.accuracy(ms.prebuilt_scores(b).select("query_id", "doc_id", "yhat"), b.answers)
    return m.select("query_id", "tp", "fp", "fn", F.round("base_rate", 6).alias("base_rate"), F.round("f1", 6).alias("f1"))


def _by_method(cols: str) -> str:
    return f"SELECT corpus, method, {cols} FROM {RUNS} GROUP BY 1, 2"


@key("sla_hits", _by_method("count(*) FILTER (WHERE accuracy >= alpha) AS hits"))
def sla_hits(spark, sf):
    return metrics.summary(runs(spark), "corpus", "method").select("corpus", "method", "hits")


@key("sla_violation", _by_method("round(sum(CASE WHEN accuracy < alpha THEN alpha - accuracy ELSE 0 END), 6)::DOUBLE AS violation"))
def sla_violation(spark, sf):
    return metrics.summary(runs(spark), "corpus", "method").select("corpus", "method", F.round("violation", 6).alias("violation"))


@key("acc_mean_min", f"SELECT corpus, method, round(avg(accuracy), 6)::DOUBLE AS mean_accuracy, round(min(accuracy), 6)::DOUBLE AS min_accuracy FROM {TABLE_RUNS} GROUP BY 1, 2")
def acc_mean_min(spark, sf):
    return metrics.summary(table_runs(spark, sf), "corpus", "method").select("corpus", "method", F.round("mean_accuracy", 6).alias("mean_accuracy"), F.round("min_accuracy", 6).alias("min_accuracy"))


@key("metric_speedup", f"""WITH m AS (SELECT corpus, method, avg(e2e_s) AS m FROM {RUNS} GROUP BY 1, 2)
    SELECT a.corpus, a.method, round(b.m / a.m, 6)::DOUBLE AS speedup FROM m a JOIN m b ON a.corpus = b.corpus AND b.method = 'cluster_vote'""")
def metric_speedup(spark, sf):
    return metrics.speedup(runs(spark), "cluster_vote").select("corpus", "method", F.round("speedup", 6).alias("speedup"))


@key("metric_headroom", f"""WITH f AS (SELECT corpus, avg(0.132 * 100) AS f FROM {RUNS} GROUP BY 1), m AS (SELECT corpus, method, avg(e2e_s) AS m FROM {RUNS} GROUP BY 1, 2)
    SELECT corpus, method, round(m / f, 6)::DOUBLE AS headroom FROM m JOIN f USING (corpus)""")
def metric_headroom(spark, sf):
    return runs(spark).groupBy("corpus", "method").agg(F.round(F.avg("e2e_s") / 13.2, 6).alias("headroom"))


@key("metric_floor_gap", f"SELECT corpus, method, round(100 * (avg(e2e_s) / min(min(e2e_s)) OVER (PARTITION BY corpus) - 1), 4)::DOUBLE AS gap_percent FROM {RUNS} GROUP BY 1, 2")
def metric_floor_gap(spark, sf):
    r = runs(spark).groupBy("corpus", "method").agg(F.avg("e2e_s").alias("m"), F.min("e2e_s").alias("lo"))
    return r.select("corpus", "method", F.round(100 * (F.col("m") / F.min("lo").over(W.partitionBy("corpus")) - 1), 4).alias("gap_percent"))


_MUST = {"cluster_vote": (0.0, 4), "prebuilt_cascade": (0.05, 0), "biencoder_cascade": (0.12, 0), "hybrid_cascade": (0.12, 0), "two_phase": (0.0, 4), "exhaustive": (1.0, 0), "bayes_floor": (0.0, 0)}


@key("metric_must_pay", "WITH n AS (SELECT count(*) AS n FROM documents) SELECT method, CAST(ceil(round(f * n, 9)) + k * greatest(ceil(round(0.005 * n, 9)), 100) AS BIGINT) AS must_pay FROM n, (VALUES " + ", ".join(f"('{m}', {f}, {k})" for m, (f, k) in _MUST.items()) + ") v(method, f, k)")
def metric_must_pay(spark, sf):
    n, cfg = table(spark, sf, "documents").count(), Config()
    rows = [(m, int(np.ceil(round(f * n, 9))) + k * cfg.vote_size(n)) for m, (f, k) in _MUST.items()]
    return spark.createDataFrame(rows, "method string, must_pay long")


@key("metric_bypass", f"SELECT corpus, count(*) FILTER (WHERE NOT phase2) AS bypassed FROM {RUNS} WHERE method = 'two_phase' GROUP BY 1")
def metric_bypass(spark, sf):
    return runs(spark).filter("method = 'two_phase'").groupBy("corpus").agg(F.count_if(~F.col("phase2")).alias("bypassed"))


@key("metric_label_fraction", f"SELECT corpus, method, query_id, round(n_oracle / 10000.0, 6)::DOUBLE AS labelled FROM {RUNS}")
def metric_label_fraction(spark, sf):
    return runs(spark).select("corpus", "method", "query_id", F.round(F.col("n_oracle") / 10000.0, 6).alias("labelled"))


# ---- framework ---------------------------------------------------------------------------------
# What each method does at each step.
MATRIX = [
    ("cluster_vote", "clusters", "per cluster", "hard", "none", "agreement", "propagate or split"),
    ("prebuilt_cascade", "single", "calibration only", "hard", "small model", "uniform margin", "confident or oracle"),
    ("biencoder_cascade", "single", "uniform", "hard", "two towers", "smoothed histogram", "threshold"),
    ("hybrid_cascade", "single", "uniform", "hard and soft", "joint, late, head", "blend by range", "threshold"),
    ("two_phase_first", "clusters", "per cluster", "hard and soft", "none", "agreement", "propagate or hand over"),
    ("two_phase_second", "single", "labels reused, stratified calibration", "hard and soft", "joint, late, head", "blend by range", "threshold"),
    ("bayes_floor", "single", "all", "soft", "the oracle", "budget", "smallest errors auto"),
]


@key("plan_matrix", "SELECT * FROM (VALUES " + ", ".join(str(r) for r in MATRIX) + ") m(method, partition_step, sample_step, label_use, proxy, calibration, deployment)")
def plan_matrix(spark, sf):
    return spark.createDataFrame(MATRIX, "method string, partition_step string, sample_step string, label_use string, proxy string, calibration string, deployment string")


@key("partition_single", "SELECT '0' AS cluster_id, count(*) AS n FROM documents")
def partition_single(spark, sf):
    return table(spark, sf, "documents").withColumn("cluster_id", F.lit("0")).groupBy("cluster_id").agg(F.count("*").alias("n"))


_SEEDS = "SELECT vec_id AS c, embedding AS e FROM embeddings WHERE vec_id IN (0, 1, 2, 3)"
_D2 = "list_sum(list_transform(list_zip({a}, {b}), lambda z: (z[1]::DOUBLE - z[2]::DOUBLE) ** 2))"


def _assign_sql(seeds: str, vectors: str = "SELECT vec_id, embedding FROM embeddings") -> str:
    return f"SELECT vec_id, arg_min(c, d) AS cluster_id FROM (SELECT v.vec_id, s.c, round({_D2.format(a='v.embedding', b='s.e')}, 9) AS d FROM ({vectors}) v, ({seeds}) s) GROUP BY vec_id"


def _vec_assign(spark, sf, centres) -> DataFrame:
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("embedding").alias("emb"))
    return clustering.assign(e, centres).select(F.col("doc_id").alias("vec_id"), F.col("cluster_id").cast("long").alias("cluster_id"))


def _seed_centres(spark, sf) -> np.ndarray:
    rows = table(spark, sf, "embeddings").filter("vec_id < 4").orderBy("vec_id").select("embedding").collect()
    return np.array([r[0] for r in rows], float)


@key("kmeans_assign", _assign_sql(_SEEDS))
def kmeans_assign(spark, sf):
    return _vec_assign(spark, sf, _seed_centres(spark, sf))


@key("kmeans_lloyd2", f"""WITH a1 AS ({_assign_sql(_SEEDS)}), x AS (SELECT vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) AS i FROM embeddings),
    c1 AS (SELECT c, list(m ORDER BY i) AS e FROM (SELECT cluster_id AS c, i, avg(v) AS m FROM a1 JOIN x USING (vec_id) GROUP BY 1, 2) GROUP BY 1), a2 AS ({_assign_sql('SELECT c, e FROM c1')}),
    c2 AS (SELECT c, list(m ORDER BY i) AS e FROM (SELECT cluster_id AS c, i, avg(v) AS m FROM a2 JOIN x USING (vec_id) GROUP BY 1, 2) GROUP BY 1) SELECT cluster_id, count(*) AS n FROM ({_assign_sql('SELECT c, e FROM c2')}) GROUP BY 1""")
def kmeans_lloyd2(spark, sf):
    c = _seed_centres(spark, sf)
    e = table(spark, sf, "embeddings")
    for _ in range(2):
        a = _vec_assign(spark, sf, c)
        mean = e.join(a, "vec_id").select("cluster_id", F.posexplode("embedding").alias("i", "v")).groupBy("cluster_id", "i").agg(F.avg(F.col("v").cast("double")).alias("m"))
        rows = mean.groupBy("cluster_id").agg(F.sort_array(F.collect_list(F.struct("i", "m"))).alias("s")).select("cluster_id", "s.m").orderBy("cluster_id").collect()
        c = np.array([r[1] for r in rows])
    return _vec_assign(spark, sf, c).groupBy("cluster_id").agg(F.count("*").alias("n"))


@key("sample_per_group", f"SELECT lang, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY {u('doc_id', chr(39) + ':' + chr(39), chr(39) + 's' + chr(39))}, doc_id) <= 7")
def sample_per_group(spark, sf):
    return hash_sample(table(spark, sf, "documents").select("doc_id", "lang"), ["lang"], 7, "s").select("lang", "doc_id")


_SPLIT = u("doc_id", "':'", "query_id", "':'", "'split'")


def _split_sql(t: str) -> str:
    return f"SELECT *, CASE WHEN {_SPLIT} < 0.07 THEN 'train' WHEN {_SPLIT} < 0.07 + 0.05 THEN 'cal' END AS part FROM {t} t"


@key("sample_train_cal", f"SELECT query_id, part, count(*) AS n, CAST(sum(doc_id) AS BIGINT) AS ids FROM ({_split_sql(truth())}) WHERE part IS NOT NULL GROUP BY 1, 2")
def sample_train_cal(spark, sf):
    return split_sample(answers(spark, sf).select("query_id", "doc_id"), 0.07, 0.05).filter("part IS NOT NULL").groupBy("query_id", "part").agg(F.count("*").alias("n"), F.sum("doc_id").alias("ids"))


_STRATA = u("doc_id", "':'", "query_id", "':'", "'strata'")


@key("sample_stratified", f"""WITH s AS (SELECT query_id, doc_id, prob, ntile(5) OVER (PARTITION BY query_id ORDER BY prob, doc_id) AS stratum FROM {truth(FEW, prebuilt=True)} t)
    SELECT query_id, CAST(stratum AS INT) AS stratum, doc_id FROM s QUALIFY row_number() OVER (PARTITION BY query_id, stratum ORDER BY {_STRATA}, doc_id) <= ceil(round(0.05 * count(*) OVER (PARTITION BY query_id, stratum), 9))""")
def sample_stratified(spark, sf):
    return stratified_sample(ms.prebuilt_scores(bench(spark, sf)), 0.05, 5).select("query_id", "stratum", "doc_id")


_SCORED = f"SELECT *, round(2 * abs(prob - 0.5), 9) AS conf, CASE WHEN prob >= 0.5 THEN 1 ELSE 0 END AS yhat FROM {truth(FEW, prebuilt=True)} t"


@key("deploy_threshold", f"SELECT query_id, CASE WHEN conf >= 0.4 THEN 'auto' ELSE 'oracle' END AS origin, count(*) AS n, CAST(sum(CASE WHEN conf >= 0.4 THEN yhat ELSE y END) AS BIGINT) AS yes FROM ({_SCORED}) GROUP BY 1, 2")
def deploy_threshold(spark, sf):
    b = bench(spark, sf)
    pred = ms.deploy(b, ms.prebuilt_scores(b), {q: th.Choice(0.4, 0, 0.0) for q in FEW}, Ledger(b.answers))
    return pred.groupBy("query_id", "origin").agg(F.count("*").alias("n"), F.sum("yhat").cast("long").alias("yes"))


# ---- voting ------------------------------------------------------------------------------------
@key("vote_sample_size", "SELECT n, greatest(CAST(ceil(round(0.005 * n, 9)) AS BIGINT), 100) AS size FROM (VALUES (1000), (10000), (20000), (50000), (1000000)) v(n)")
def vote_sample_size(spark, sf):
    cfg = Config()
    return spark.createDataFrame([(n, cfg.vote_size(n)) for n in (1000, 10000, 20000, 50000, 1000000)], "n int, size long")


_VOTES = f"""SELECT t.query_id, d.lang AS cluster_id, t.doc_id, t.y FROM {truth()} t JOIN documents d USING (doc_id)
    QUALIFY row_number() OVER (PARTITION BY t.query_id, d.lang ORDER BY {u('doc_id', "':'", "'vote0'")}, t.doc_id) <= 20"""
_TALLY = f"SELECT query_id, cluster_id, count(*) AS n, CAST(sum(y) AS BIGINT) AS yes, round(greatest(avg(y), 1 - avg(y)), 6)::DOUBLE AS agreement FROM ({_VOTES}) GROUP BY 1, 2"


def _votes(spark, sf) -> DataFrame:
    pairs = answers(spark, sf).join(table(spark, sf, "documents").select("doc_id", F.col("lang").alias("cluster_id")), "doc_id")
    return hash_sample(pairs, ["query_id", "cluster_id"], 20, "vote0").select("query_id", "cluster_id", "doc_id", "y")


def _tally(votes: DataFrame) -> DataFrame:
    return votes.groupBy("query_id", "cluster_id").agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("yes"), F.round(F.greatest(F.avg("y"), 1 - F.avg("y")), 6).alias("agreement"))


@key("vote_labels", _VOTES)
def vote_labels(spark, sf):
    return _votes(spark, sf)


@key("vote_agreement", _TALLY)
def vote_agreement(spark, sf):
    return _tally(_votes(spark, sf))


@key("vote_propagate", f"""WITH v AS ({_VOTES}), m AS ({_TALLY}) SELECT t.query_id, CASE WHEN v.y IS NOT NULL THEN 'oracle' WHEN m.agreement >= 0.9 THEN 'propagated' ELSE 'open' END AS origin, count(*) AS n,
    CAST(sum(coalesce(v.y, CASE WHEN m.agreement >= 0.9 THEN CASE WHEN 2 * m.yes >= m.n THEN 1 ELSE 0 END END, 0)) AS BIGINT) AS yes
    FROM {truth()} t JOIN documents d USING (doc_id) JOIN m ON m.query_id = t.query_id AND m.cluster_id = d.lang LEFT JOIN v ON v.query_id = t.query_id AND v.doc_id = t.doc_id GROUP BY 1, 2""")
def vote_propagate(spark, sf):
    votes = save(_votes(spark, sf))
    tally = [r.asDict() for r in _tally(votes).collect()]
    members = answers(spark, sf).select("query_id", "doc_id").join(table(spark, sf, "documents").select("doc_id", F.col("lang").alias("cluster_id")), "doc_id")
    won = {(r["query_id"], r["cluster_id"]): int(2 * r["yes"] >= r["n"]) for r in tally if r["agreement"] >= 0.9}
    led = Ledger(votes)
    led.rows = votes.select("query_id", "doc_id", "y")
    got = ms.propagate(bench(spark, sf), ms.Vote(members, won, set(), []), led)
    origin = F.when(F.col("yhat").isNull(), "open").otherwise(F.col("origin"))
    return got.groupBy("query_id", origin.alias("origin")).agg(F.count("*").alias("n"), F.sum(F.coalesce("yhat", F.lit(0))).cast("long").alias("yes"))


@key("vote_split_step", f"""WITH s AS (SELECT label, arg_min(embedding, vec_id) AS a, arg_max(embedding, vec_id) AS b FROM embeddings GROUP BY 1)
    SELECT concat(e.label, CASE WHEN {_D2.format(a='e.embedding', b='s.a')} <= {_D2.format(a='e.embedding', b='s.b')} THEN '.0' ELSE '.1' END) AS cluster_id, count(*) AS n FROM embeddings e JOIN s USING (label) GROUP BY 1""")
def vote_split_step(spark, sf):
    e = table(spark, sf, "embeddings")
    seeds = e.groupBy("label").agg(F.min_by("embedding", "vec_id").alias("a"), F.max_by("embedding", "vec_id").alias("b"))
    d = "aggregate(zip_with(embedding, {c}, (x, y) -> (cast(x as double) - y) * (cast(x as double) - y)), 0D, (s, v) -> s + v)"
    side = F.expr(f"CASE WHEN {d.format(c='a')} <= {d.format(c='b')} THEN '.0' ELSE '.1' END")
    return e.join(F.broadcast(seeds), "label").groupBy(F.concat(F.col("label").cast("string"), side).alias("cluster_id")).agg(F.count("*").alias("n"))


@key("vote_agreement_examples", f"SELECT query_id, lang, round(greatest(avg(y), 1 - avg(y)), 6)::DOUBLE AS agreement FROM {truth(('Q01', 'Q02', 'Q18', 'Q20'))} t JOIN documents USING (doc_id) GROUP BY 1, 2")
def vote_agreement_examples(spark, sf):
    a = answers(spark, sf, ("Q01", "Q02", "Q18", "Q20")).join(table(spark, sf, "documents").select("doc_id", "lang"), "doc_id")
    return a.groupBy("query_id", "lang").agg(F.round(F.greatest(F.avg("y"), 1 - F.avg("y")), 6).alias("agreement"))


@key("vote_round_trace")
def vote_round_trace(spark, sf):
    b = bench(spark, sf, ("Q01", "Q19"))
    return spark.createDataFrame(pd.DataFrame(ms.vote(b, Ledger(b.answers), b.cfg.phase1_frac).rounds))


@key("vote_rho_sweep")
def vote_rho_sweep(spark, sf):
    out = []
    for rho in (0.8, 0.95):
        b = bench(spark, sf, ("Q01", "Q03"), rho=rho)
        v = ms.vote(b, Ledger(b.answers), b.cfg.phase1_frac)
        out.append((rho, len(v.majority), len(v.open_)))
    return spark.createDataFrame(out, "rho double, agreed int, left_open int")


# ---- scorers -----------------------------------------------------------------------------------
@key("prebuilt_scores", f"SELECT query_id, doc_id, round(prob, 6) AS prob FROM {truth(FEW, prebuilt=True)} t")
def prebuilt_scores(spark, sf):
    return answers(spark, sf).select("query_id", "doc_id", F.round("prob", 6).alias("prob"))


_POINTS = "(SELECT * FROM (VALUES (0.6e0, 0.2e0), (0.9e0, 0.8e0), (0.1e0, 0.5e0), (0.5e0, 0.5e0)) v(js, li))"


def _points(spark) -> pd.DataFrame:
    return spark.sql(f"SELECT * FROM {_POINTS}").toPandas()


@key("head_features", f"SELECT js, li, round(js * li, 6) AS product, round(abs(js - li), 6) AS gap, round(js * js, 6) AS js2, round(li * li, 6) AS li2 FROM {_POINTS}")
def head_features(spark, sf):
    f = nets.head_features(*_points(spark).to_numpy().T).round(6)
    return spark.createDataFrame(pd.DataFrame(f, columns=["js", "li", "product", "gap", "js2", "li2"]))


@key("head_forward", f"SELECT js, li, round(1 / (1 + exp(-(0.8 * greatest(0, js + li - 0.5) - 1.2 * greatest(0, js - 2 * li) + 0.1))), 6)::DOUBLE AS prob FROM {_POINTS}")
def head_forward(spark, sf):
    net = nets.MLP([6, 2, 1], 0)
    net.params = [np.array([[1.0, 1], [1, -2], [0, 0], [0, 0], [0, 0], [0, 0]]), np.array([-0.5, 0.0]), np.array([[0.8], [-1.2]]), np.array([0.1])]
    p = _points(spark)
    p["prob"] = nets.sigmoid(net.forward(nets.head_features(p["js"].to_numpy(), p["li"].to_numpy()))[:, 0]).round(6)
    return spark.createDataFrame(p)


@key("joint_forward", f"SELECT js, li, round(1 / (1 + exp(-(1.5 * greatest(0, 0.3 * 0.5 + 0.7 * js + 0.5 * js - abs(0.5 - js)) - 0.2))), 6)::DOUBLE AS prob FROM {_POINTS}")
def joint_forward(spark, sf):
    p, s = _points(spark), nets.JointScorer(1, 1)
    s.net.params = [np.array([[0.3], [0.7], [1.0], [-1.0]]), np.zeros(1), np.array([[1.5]]), np.array([-0.2])]
    p["prob"] = s.prob(np.array([0.5]), p[["js"]].to_numpy()).round(6)
    return spark.createDataFrame(p)


@key("biencoder_forward", """SELECT vec_id, round((0.6e0 * x + 0.8e0 * y) / ((1 + 1e-9) * (sqrt(x * x + y * y) + 1e-9)), 5)::DOUBLE AS cosine FROM (SELECT vec_id, greatest(embedding[1]::DOUBLE, 0) AS x, greatest(embedding[2]::DOUBLE, 0) AS y
    FROM embeddings WHERE embedding[1] IS NOT NULL AND embedding[2] IS NOT NULL)""")
def biencoder_forward(spark, sf):
    """Towers that let positive values through, on the first two components of every vector."""
    m = nets.BiEncoder(2, 2, 2)
    eye = [np.eye(2), np.zeros(2), np.eye(2), np.zeros(2)]
    m.q.params, m.d.params = eye, [x.copy() for x in eye]

    def run(parts):
        for p in parts:
            yield pd.DataFrame({"vec_id": p["vec_id"], "cosine": m.cosine(np.array([0.6, 0.8]), p[["x", "y"]].to_numpy(float)).round(5)})

    two = table(spark, sf, "embeddings").select("vec_id", *[F.get("embedding", F.lit(k)).cast("double").alias(c) for k, c in enumerate("xy")])
    return two.filter("x IS NOT NULL AND y IS NOT NULL").mapInPandas(run, "vec_id long, cosine double")


@key("maxsim_score", "SELECT doc_id, round(sum(best), 6)::DOUBLE AS score FROM (SELECT d.doc_id, q.t, max(q.x * d.x + q.y * d.y) AS best FROM (VALUES (1, 0.8, 0.6), (1, 0.0, 1.0), (1, 0.0, 1.0), (2, 0.6, 0.8)) d(doc_id, x, y), (VALUES (0, 1.0, 0.0), (1, 0.0, 1.0)) q(t, x, y) GROUP BY 1, 2) GROUP BY 1")
def maxsim_score(spark, sf):
    q = np.eye(2)
    docs = {1: [[0.8, 0.6], [0.0, 1.0], [0.0, 1.0]], 2: [[0.6, 0.8]]}
    return spark.createDataFrame([(d, round(nets.maxsim(q, np.array(t)), 6)) for d, t in docs.items()], "doc_id int, score double")


@key("conf_score", f"SELECT js, round(2 * abs(js - 0.5), 6)::DOUBLE AS conf FROM {_POINTS}")
def conf_score(spark, sf):
    p = _points(spark)
    return spark.createDataFrame(pd.DataFrame({"js": p["js"], "conf": nets.confidence(p["js"].to_numpy()).round(6)}))


def _of_sums(spark, sf, f, name: str) -> DataFrame:
    """A number of each query from the sums of its losses; one row a query reaches the driver."""
    sums = metrics.loss_sums(answers(spark, sf)).orderBy("query_id").collect()
    return spark.createDataFrame([(r["query_id"], None if (v := f(r)) is None else round(float(v), 6)) for r in sums], f"query_id string, {name} double")


def _soft(r):
    return r["soft"] / r["n_soft"] if r["n_soft"] else None


def _risk(r):
    return nets.soft_risk_of(r["wrong"], r["conf"])


def _penalty(r):
    return nets.sla_penalty(_risk(r), 0.99, 0.5)


def _cover(r):
    return 1 - r["conf"] / r["n"]


_CLIP = "least(greatest(prob, 1e-7), 1 - 1e-7)"
_BCE = "round(avg(-{t} * ln({c}) - (1 - {t}) * ln(1 - {c})), 6)::DOUBLE"


@key("loss_soft", f"SELECT query_id, {_BCE.format(t='p_star', c=_CLIP)} AS loss FROM {truth(FEW, prebuilt=True)} t GROUP BY 1")
def loss_soft(spark, sf):
    return _of_sums(spark, sf, _soft, "loss")


@key("loss_hard", f"SELECT query_id, {_BCE.format(t='y', c=_CLIP)} AS loss FROM {truth(FEW, prebuilt=True)} t GROUP BY 1")
def loss_hard(spark, sf):
    return _of_sums(spark, sf, lambda r: r["hard"] / r["n"], "loss")


_RISK = f"SELECT query_id, sum(c * w) / (sum(c) + 0.001) AS risk, 1 - avg(c) AS cover, avg(-p_star * ln({_CLIP}) - (1 - p_star) * ln(1 - {_CLIP})) AS soft FROM (SELECT *, 2 * abs(prob - 0.5) AS c, CASE WHEN y = 1 THEN 1 - prob ELSE prob END AS w FROM {truth(FEW, prebuilt=True)} t) GROUP BY 1"


@key("risk_soft", f"SELECT query_id, round(risk, 6)::DOUBLE AS risk FROM ({_RISK})")
def risk_soft(spark, sf):
    return _of_sums(spark, sf, _risk, "risk")


@key("loss_sla_penalty", f"SELECT query_id, round(0.5 * greatest(0, risk - 0.01), 6)::DOUBLE AS penalty FROM ({_RISK})")
def loss_sla_penalty(spark, sf):
    return _of_sums(spark, sf, _penalty, "penalty")


@key("loss_coverage", f"SELECT query_id, round(cover, 6)::DOUBLE AS loss FROM ({_RISK})")
def loss_coverage(spark, sf):
    return _of_sums(spark, sf, _cover, "loss")


@key("loss_total", f"SELECT query_id, round(soft + 0.35 * cover + 0.5 * greatest(0, risk - 0.01), 6)::DOUBLE AS loss FROM ({_RISK})")
def loss_total(spark, sf):
    def total(r):
        soft = _soft(r)
        return None if soft is None else nets.total_loss(soft, _cover(r), _penalty(r))

    return _of_sums(spark, sf, total, "loss")


@key("dual_trace", """WITH RECURSIVE r AS (SELECT i, 0.05 + 0.3 / (i + 1) AS risk FROM range(20) t(i)), d AS (SELECT -1::BIGINT AS i, 0.01::DOUBLE AS dual UNION ALL
    SELECT r.i, least(10.0, greatest(0.0, d.dual + 0.5 * (r.risk - 0.1)))::DOUBLE FROM d JOIN r ON r.i = d.i + 1) SELECT i AS epoch, round(dual, 6)::DOUBLE AS dual FROM d WHERE i >= 0""")
def dual_trace(spark, sf):
    dual, out = 0.01, []
    for i in range(20):
        dual = nets.dual_step(dual, 0.05 + 0.3 / (i + 1), 0.1)
        out.append((i, round(dual, 6)))
    return spark.createDataFrame(out, "epoch long, dual double")


@key("diag_separability", f"""WITH s AS (SELECT query_id, y, prob, rank() OVER (PARTITION BY query_id ORDER BY prob) + (count(*) OVER (PARTITION BY query_id, prob) - 1) / 2.0 AS r FROM {truth(FEW, prebuilt=True)} t)
    SELECT query_id, round((sum(r) FILTER (WHERE y = 1) - sum(y) * (sum(y) + 1) / 2.0) / (sum(y) * (count(*) - sum(y))), 6)::DOUBLE AS auc, round(avg(prob) FILTER (WHERE y = 1) - avg(prob) FILTER (WHERE y = 0), 6)::DOUBLE AS gap FROM s GROUP BY 1""")
def diag_separability(spark, sf):
    s = answers(spark, sf).select("query_id", "y", "prob")
    ties = F.count("*").over(W.partitionBy("query_id", "prob"))
    s = s.withColumn("r", F.rank().over(W.partitionBy("query_id").orderBy("prob")) + (ties - 1) / 2)
    n1 = F.sum("y")
    return s.groupBy("query_id").agg(F.round((F.sum(F.when(F.col("y") == 1, F.col("r"))) - n1 * (n1 + 1) / 2) / (n1 * (F.count("*") - n1)), 6).alias("auc"), F.round(F.avg(F.when(F.col("y") == 1, F.col("prob"))) - F.avg(F.when(F.col("y") == 0, F.col("prob"))), 6).alias("gap"))


def _moments(batches):
    """Count, sums and products of a partition's vectors, as one row an entry."""
    total = None
    for batch in batches:
        if len(batch):
            x = np.stack(batch["emb"].to_numpy()).astype(float)
            x = np.concatenate([np.ones((len(x), 1)), x], axis=1)
            total = x.T @ x if total is None else total + x.T @ x
    if total is not None:
        yield pd.DataFrame({"k": np.arange(total.size), "v": total.ravel()})


def pca2(vectors: DataFrame, dim: int) -> DataFrame:
    """Every vector on the two main axes of all of them, ``doc_id, x, y``; the largest weight of an axis is positive.

    Only ``(dim + 1)^2`` sums reach the driver, however many vectors there are; an empty table gives no rows.
    """
    rows = vectors.select("emb").mapInPandas(_moments, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).orderBy("k").toPandas()
    if rows.empty:
        return vectors.select("doc_id", F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))
    m = rows["v"].to_numpy().reshape(dim + 1, dim + 1) / rows["v"][0]
    mean = m[0, 1:]
    axes = np.linalg.eigh(m[1:, 1:] - np.outer(mean, mean))[1][:, ::-1][:, :2].T
    axes = axes * np.sign(axes[np.arange(2), np.abs(axes).argmax(axis=1)])[:, None]

    def along(axis) -> F.Column:
        dot = F.aggregate(F.zip_with("emb", F.lit(axis.tolist()), lambda a, b: a.cast("double") * b), F.lit(0.0), lambda a, b: a + b)
        return F.round(dot - float(axis @ mean), 6)

    return vectors.select("doc_id", along(axes[0]).alias("x"), along(axes[1]).alias("y"))


@key("diag_pca2")
def diag_pca2(spark, sf):
    b = bench(spark, sf, ("Q01",))
    return pca2(b.features, b.cfg.emb_dim)


# ---- Bayes error -------------------------------------------------------------------------------
@key("ber_eta", f"SELECT query_id, doc_id, round(least(p_star, 1 - p_star), 6)::DOUBLE AS eta FROM {truth()} t")
def ber_eta(spark, sf):
    return answers(spark, sf).select("query_id", "doc_id", F.round(bayes.eta(F.col("p_star")), 6).alias("eta"))


@key("ber_query", f"SELECT query_id, round(avg(least(p_star, 1 - p_star)), 6)::DOUBLE AS ber FROM {truth(cat.ALL)} t GROUP BY 1")
def ber_query(spark, sf):
    return bayes.query_ber(answers(spark, sf, cat.ALL)).select("query_id", F.round("ber", 6).alias("ber"))


@key("ber_pilot", f"SELECT query_id, count(*) AS n, round(avg(e), 6)::DOUBLE AS ber, round(stddev_samp(e) / sqrt(count(*)), 6)::DOUBLE AS std_error FROM (SELECT query_id, least(p_star, 1 - p_star) AS e FROM {truth()} t WHERE {u('doc_id', chr(39) + ':pilot' + chr(39))} < 0.15) GROUP BY 1")
def ber_pilot(spark, sf):
    return bayes.pilot_ber(answers(spark, sf).filter(uniform(F.col("doc_id"), ":pilot") < 0.15)).select("query_id", "n", F.round("ber", 6).alias("ber"), F.round("std_error", 6).alias("std_error"))


def _floor_sql(alphas, queries=HARD) -> str:
    vals = ", ".join(f"({a}::DOUBLE)" for a in alphas)
    return f"""SELECT query_id, alpha, max(n) AS n_docs, max(n) - count(*) FILTER (WHERE s <= (1 - alpha) * n + 1e-9) AS floor_calls FROM (SELECT query_id, alpha, count(*) OVER (PARTITION BY query_id, alpha) AS n,
        sum(round(least(p_star, 1 - p_star), 9)) OVER (PARTITION BY query_id, alpha ORDER BY round(least(p_star, 1 - p_star), 9), doc_id) AS s FROM {truth(queries)} t, (VALUES {vals}) a(alpha)) GROUP BY 1, 2"""


@key("ber_floor", _floor_sql((0.9,)))
def ber_floor(spark, sf):
    return bayes.bayes_floor(answers(spark, sf, HARD), [0.9])


@key("ber_floor_curve", _floor_sql(ALPHAS))
def ber_floor_curve(spark, sf):
    return bayes.bayes_floor(answers(spark, sf, HARD), list(ALPHAS))


@key("ber_floor_cost", f"SELECT query_id, round(floor_calls * 0.132, 6)::DOUBLE AS seconds FROM ({_floor_sql((0.9,))})")
def ber_floor_cost(spark, sf):
    return ber_floor(spark, sf).select("query_id", F.round(F.col("floor_calls") * 0.132, 6).alias("seconds"))


def _wins(spark) -> pd.DataFrame:
    r = metrics.envelope(runs(spark).filter("method IN ('cluster_vote', 'hybrid_cascade')")).filter("method = 'cluster_vote'")
    return r.select("corpus", "query_id", "ber", F.col("wins").alias("win")).toPandas().sort_values(["corpus", "query_id"])


@key("compass_fit")
def compass_fit(spark, sf):
    return spark.createDataFrame(pd.DataFrame([bayes.compass(_wins(spark))]))


@key("compass_crossover")
def compass_crossover(spark, sf):
    w = _table_wins(spark, sf)
    return spark.createDataFrame([(c, float(bayes.compass(g)["crossover"])) for c, g in w.groupby("corpus")], "corpus string, crossover double")


_WIN = f"SELECT corpus, query_id, any_value(ber) AS ber, CASE WHEN arg_min(method, e2e_s) = 'cluster_vote' THEN 1 ELSE 0 END AS win FROM {RUNS} WHERE method IN ('cluster_vote', 'hybrid_cascade') GROUP BY 1, 2"


_TABLE_WIN = f"SELECT corpus, query_id, any_value(ber) AS ber, CASE WHEN arg_min(method, e2e_s) = 'cluster_vote' THEN 1 ELSE 0 END AS win FROM {TABLE_RUNS} WHERE method IN ('cluster_vote', 'hybrid_cascade') GROUP BY 1, 2"


def _table_wins(spark, sf) -> pd.DataFrame:
    """Where voting is cheaper on the given documents: a row a language and predicate."""
    r = metrics.envelope(table_runs(spark, sf).filter("method IN ('cluster_vote', 'hybrid_cascade')")).filter("method = 'cluster_vote'")
    return r.select("corpus", "query_id", "ber", F.col("wins").alias("win")).toPandas().sort_values(["corpus", "query_id"])


@key("compass_auc", f"WITH w AS ({_TABLE_WIN}) SELECT coalesce(round(avg(CASE WHEN a.ber < b.ber THEN 1.0 WHEN a.ber = b.ber THEN 0.5 ELSE 0.0 END), 6), 0.5)::DOUBLE AS auc FROM w a, w b WHERE a.win = 1 AND b.win = 0")
def compass_auc(spark, sf):
    w = _table_wins(spark, sf)
    return spark.createDataFrame([(round(bayes.auc(-w["ber"].to_numpy(), w["win"].to_numpy()), 6),)], "auc double")


@key("compass_outliers", f"SELECT corpus, query_id, ber FROM ({_WIN}) WHERE win = 1 AND ber > 0.005")
def compass_outliers(spark, sf):
    w = _wins(spark)
    return spark.createDataFrame(w[(w["win"] == 1) & (w["ber"] > 0.005)][["corpus", "query_id", "ber"]])


_GRID = ", ".join(f"({g / 100}::DOUBLE)" for g in range(0, 11, 2))


@key("fig_latency_vs_ber", f"SELECT method, g, round(sum(e2e_s * exp(-0.5 * ((ber - g) / 0.02) ** 2)) / sum(exp(-0.5 * ((ber - g) / 0.02) ** 2)), 6)::DOUBLE AS e2e_s FROM {RUNS}, (VALUES {_GRID}) v(g) GROUP BY 1, 2")
def fig_latency_vs_ber(spark, sf):
    g = spark.createDataFrame([(k / 100,) for k in range(0, 11, 2)], "g double")
    w = F.exp(-0.5 * F.pow((F.col("ber") - F.col("g")) / 0.02, 2))
    return runs(spark).crossJoin(F.broadcast(g)).groupBy("method", "g").agg(F.round(F.sum(F.col("e2e_s") * w) / F.sum(w), 6).alias("e2e_s"))


@key("ber_buckets", f"SELECT corpus, query_id, CASE ntile(3) OVER (PARTITION BY corpus ORDER BY ber, query_id) WHEN 1 THEN 'easy' WHEN 2 THEN 'medium' ELSE 'hard' END AS bucket FROM (SELECT DISTINCT corpus, query_id, ber FROM {TABLE_RUNS})")
def ber_buckets(spark, sf):
    t = F.ntile(3).over(W.partitionBy("corpus").orderBy("ber", "query_id"))
    return table_runs(spark, sf).select("corpus", "query_id", "ber").distinct().select("corpus", "query_id", F.element_at(F.array(F.lit("easy"), F.lit("medium"), F.lit("hard")), t).alias("bucket"))
