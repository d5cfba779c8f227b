"""Queries of calibration, whole methods and experiments."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import bayes, metrics
from ..calibrate import bounds
from ..calibrate import threshold as th
from ..cascades import methods as ms
from ..config import Config
from ..oracle import Ledger, StoredOracle, uniform
from ..sampling import split_sample
from ..sources import catalogue as cat
from ..sources.tables import table
from .method_queries import ALPHAS, HARD, LEDGER, RUNS, _floor_sql, _split_sql, bench, runs, truth, u
from .registry import key

#: A fixed threshold at which single steps of the calibration are shown.
TAU = 0.3

# ---- the naive formulation in SQL: every threshold, every range, every document ------------------
_S = f"SELECT query_id, doc_id, y, prob, round(2 * abs(prob - 0.5), 9) AS conf, CASE WHEN prob >= 0.5 THEN 1 ELSE 0 END AS yhat, part FROM ({_split_sql(truth(HARD, prebuilt=True))})"
_BASE = f"""s AS MATERIALIZED ({_S}), c AS MATERIALIZED (SELECT *, CASE WHEN y <> yhat THEN 1 ELSE 0 END AS wrong FROM s WHERE part = 'cal'), pool AS MATERIALIZED (SELECT * FROM s WHERE part IS DISTINCT FROM 'cal'),
    quant AS (SELECT query_id, unnest(list_distinct(list_concat(list_transform(quantile_cont(conf, {[round(k / 199, 12) if k not in (0, 199) else float(k // 199) for k in range(200)]}), lambda x: round(x, 9)), [0.0, 0.5, 1.0]))) AS tau FROM c GROUP BY 1)"""
_BINS = {
    "per_threshold": """tile AS (SELECT q.query_id, q.tau, c.conf, ntile(20) OVER (PARTITION BY q.query_id, q.tau ORDER BY c.conf) AS t FROM taus q JOIN c ON c.query_id = q.query_id AND c.conf >= q.tau),
        edge AS (SELECT DISTINCT query_id, tau, min(conf) AS lo FROM tile GROUP BY query_id, tau, t), low AS (SELECT query_id, tau, CASE WHEN lo = min(lo) OVER (PARTITION BY query_id, tau) THEN tau ELSE lo END AS lo FROM edge
        UNION SELECT query_id, tau, tau FROM taus)""",
    "global": """tile AS (SELECT query_id, conf, ntile(20) OVER (PARTITION BY query_id ORDER BY conf) AS t FROM c), edge AS (SELECT DISTINCT query_id, min(conf) AS lo FROM tile GROUP BY query_id, t),
        low AS (SELECT q.query_id, q.tau, e.lo FROM taus q JOIN edge e ON e.query_id = q.query_id AND e.lo > q.tau UNION SELECT query_id, tau, tau FROM taus)""",
    "one": "low AS (SELECT query_id, tau, tau AS lo FROM taus)",
    "grid": "low AS (SELECT q.query_id, q.tau, g.i / 64.0::DOUBLE AS lo FROM taus q JOIN range(64) g(i) ON g.i / 64.0::DOUBLE > q.tau UNION SELECT query_id, tau, tau FROM taus)",
}
_COUNT = """bin AS (SELECT query_id, tau, lo, lead(lo, 1, 9.0) OVER (PARTITION BY query_id, tau ORDER BY lo) AS hi FROM low),
    cnt AS (SELECT b.query_id, b.tau, b.lo, b.hi, count(c.conf) AS n, coalesce(sum(c.wrong), 0)::BIGINT AS k FROM bin b LEFT JOIN c ON c.query_id = b.query_id AND c.conf >= b.lo AND c.conf < b.hi GROUP BY ALL),
    pc AS MATERIALIZED (SELECT b.*, (SELECT count(*) FROM pool p WHERE p.query_id = b.query_id AND p.conf >= b.lo AND p.conf < b.hi) AS m FROM cnt b)"""
_UPPER = """kn AS (SELECT DISTINCT k, n FROM pc), r AS (SELECT k, n, k * 1.0::DOUBLE / n AS lo, 1.0::DOUBLE AS hi, 0 AS i FROM kn WHERE n > 0 AND k > 0 AND k < n
    UNION ALL SELECT k, n, CASE WHEN tail > {d} THEN (lo + hi) / 2 ELSE lo END, CASE WHEN tail > {d} THEN hi ELSE (lo + hi) / 2 END, i + 1 FROM (SELECT *, (SELECT sum(exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln((lo + hi) / 2) + (n - j) * ln(1 - (lo + hi) / 2))) FROM range(k + 1) g(j)) AS tail FROM r WHERE i < 45)),
    ub AS (SELECT k, n, (lo + hi) / 2 AS u FROM r WHERE i = 45 UNION ALL SELECT k, n, CASE WHEN n = 0 OR k = n THEN 1.0 ELSE 1 - {d} ** (1.0 / n) END FROM kn WHERE n = 0 OR k = 0 OR k = n)"""
_RATE = {
    "blend": "(1 - 0.06) * coalesce(k * 1.0 / nullif(n, 0), 1) + 0.06 * u", "naive": "coalesce(k * 1.0 / nullif(n, 0), 1)", "range_bound": "u", "uniform_margin": "u",
    "hoeffding": "CASE WHEN n = 0 THEN 1 ELSE least(1, k * 1.0 / n + sqrt(ln(1 / 0.05) / (2 * n))) END", "smoothed_histogram": "(k + 1.0) / (n + 2.0)",
}
_GRID = {"uniform_margin": "one", "hoeffding": "one", "smoothed_histogram": "grid"}


def chain(method: str, taus: str = "SELECT * FROM quant", binning: str = "per_threshold") -> str:
    """CTEs down to ``rate``: counts and rate of every range of every threshold."""
    return f"WITH RECURSIVE {_BASE}, taus AS ({taus}), {_BINS[_GRID.get(method, binning)]}, {_COUNT}, {_UPPER.format(d='0.05')}, rate AS (SELECT pc.*, ub.u, {_RATE[method]} AS rate FROM pc JOIN ub USING (k, n))"


def choice(method: str, alphas=(0.9,), binning: str = "per_threshold") -> str:
    """The chosen threshold of each query and target; infinite (shown as 9) if none is feasible."""
    vals = ", ".join(f"({a}::DOUBLE)" for a in alphas)
    return f"""{chain(method, binning=binning)}, e AS (SELECT query_id, tau, sum(CASE WHEN m > 0 THEN m * rate ELSE 0 END) AS err, sum(m) AS auto FROM rate GROUP BY 1, 2), a AS (SELECT * FROM (VALUES {vals}) v(alpha)),
        q AS (SELECT query_id, count(*) AS n_all, count(*) FILTER (WHERE part IS DISTINCT FROM 'cal') AS n_pool FROM s GROUP BY 1),
        ok AS (SELECT q.query_id, a.alpha, e.tau, e.err, q.n_pool - e.auto AS cascade, row_number() OVER (PARTITION BY q.query_id, a.alpha ORDER BY q.n_pool - e.auto, e.tau) AS o FROM q, a, e WHERE e.query_id = q.query_id AND e.auto > 0 AND e.err <= (1 - a.alpha) * q.n_all + 1e-9)
        SELECT q.query_id, a.alpha, round(coalesce(ok.tau, 9), 6)::DOUBLE AS tau, CAST(coalesce(ok.cascade, q.n_pool) AS BIGINT) AS cascade, round(coalesce(ok.err, 0), 6)::DOUBLE AS expected_errors FROM q CROSS JOIN a LEFT JOIN ok ON ok.query_id = q.query_id AND ok.alpha = a.alpha AND ok.o = 1"""


# ---- our kernel ----------------------------------------------------------------------------------
def cal_bench(spark, sf, **changes):
    """Hard queries under the prebuilt scorer with 5 % of labels for calibration."""
    b = bench(spark, sf, HARD, **changes)
    led = Ledger(b.answers)
    cal = led.request(split_sample(b.pairs(), b.cfg.train_frac, b.cfg.cal_frac).filter("part = 'cal'"), "cal")
    return b, ms.prebuilt_scores(b), cal, led


def chosen(spark, sf, method: str, alphas=(0.9,), **changes) -> DataFrame:
    b, scores, cal, led = cal_bench(spark, sf, **changes)
    rows = []
    for a in alphas:
        for q, c in ms.calibrate(replace(b, cfg=replace(b.cfg, alpha=a)), scores, cal, led.rows, method).items():
            rows.append((q, a, min(c.tau, 9.0), c.cascade, round(c.expected_errors, 6)))
    return spark.createDataFrame(rows, "query_id string, alpha double, tau double, cascade long, expected_errors double").withColumn("tau", F.round("tau", 6))


for _key, _m in {"cal_select_tau": "blend", "cal_naive": "naive", "cal_uniform_margin": "uniform_margin", "cal_hoeffding": "hoeffding", "cal_range_bound": "range_bound", "cal_smoothed_hist": "smoothed_histogram"}.items():

    @key(_key, choice(_m))
    def _chosen(spark, sf, m=_m):
        return chosen(spark, sf, m)


@key("cal_select_tau_global", choice("blend", binning="global"))
def cal_select_tau_global(spark, sf):
    return chosen(spark, sf, "blend", binning="global")


@key("cal_infeasible", choice("hoeffding", (0.99,)))
def cal_infeasible(spark, sf):
    return chosen(spark, sf, "hoeffding", (0.99,))


def _labels(spark, sf) -> dict[str, pd.DataFrame]:
    _, scores, cal, _ = cal_bench(spark, sf)
    got = scores.join(cal.select("query_id", "doc_id", "y"), ["query_id", "doc_id"]).withColumn("wrong", (F.col("yhat") != F.col("y")).cast("int")).toPandas()
    return {q: g for q, g in got.groupby("query_id")}


@key("cal_candidates", f"WITH {_BASE} SELECT query_id, count(*) AS n, round(sum(tau), 5)::DOUBLE AS total FROM quant GROUP BY 1")
def cal_candidates(spark, sf):
    return spark.createDataFrame([(q, len(t := th.candidates(g["conf"].to_numpy())), round(float(t.sum()), 5)) for q, g in _labels(spark, sf).items()], "query_id string, n long, total double")


@key("cal_accepted", f"WITH {_BASE} SELECT query_id, count(*) AS n, sum(wrong)::BIGINT AS k FROM c WHERE conf >= {TAU} GROUP BY 1")
def cal_accepted(spark, sf):
    rows = [(q, int((g["conf"] >= TAU).sum()), int(g.loc[g["conf"] >= TAU, "wrong"].sum())) for q, g in _labels(spark, sf).items()]
    return spark.createDataFrame(rows, "query_id string, n long, k long")


def _bins(spark, sf, cfg: Config | None = None) -> pd.DataFrame:
    """Ranges of the fixed threshold with everything that is known of them."""
    b, scores, cal, led = cal_bench(spark, sf)
    cfg, groups = cfg or b.cfg, _labels(spark, sf)
    cuts = {q: th.cut_points(np.round(g["conf"].to_numpy(), 9), cfg) for q, g in groups.items()}
    cuts = {q: np.unique(np.append(np.append(c, TAU), th.edges_for(np.round(groups[q]["conf"].to_numpy(), 9), TAU, cfg))) for q, c in cuts.items()}
    counts = th.pool_counts(scores.join(led.rows.select("query_id", "doc_id"), ["query_id", "doc_id"], "left_anti"), cuts)
    out = []
    for q, g in groups.items():
        conf, wrong = np.round(g["conf"].to_numpy(), 9), g["wrong"].to_numpy()
        edges = th.edges_for(conf, TAU, cfg)
        at = np.searchsorted(edges, conf, side="right") - 1
        up = th.at_least(cuts[q], counts[q], edges)
        pool = up - np.append(up[1:], 0)
        n = np.bincount(at[at >= 0], minlength=len(edges))
        k = np.bincount(at[at >= 0], weights=wrong[at >= 0], minlength=len(edges)).astype(int)
        rate = bounds.blended(k, n, cfg.blend, cfg.delta)
        emp = np.where(n > 0, k / np.maximum(n, 1), 1.0)
        out.append(pd.DataFrame({"query_id": q, "lo": edges.round(6), "n": n, "k": k, "m": pool, "emp": emp.round(6), "rate": rate.round(6), "err": (pool * rate)}))
    return pd.concat(out)


_AT_TAU = chain("blend", f"SELECT DISTINCT query_id, {TAU}::DOUBLE AS tau FROM c")
for _key, _cols in {"cal_bins": "round(lo, 6)::DOUBLE AS lo", "cal_bin_counts": "round(lo, 6)::DOUBLE AS lo, n, k", "cal_empirical": "round(lo, 6)::DOUBLE AS lo, round(coalesce(k * 1.0 / nullif(n, 0), 1), 6)::DOUBLE AS emp", "cal_blend": "round(lo, 6)::DOUBLE AS lo, round(rate, 6)::DOUBLE AS rate", "cal_pool_counts": "round(lo, 6)::DOUBLE AS lo, m"}.items():

    @key(_key, f"{_AT_TAU} SELECT query_id, {_cols} FROM rate")
    def _bin_step(spark, sf, names=tuple(c.split(" AS ")[-1].strip() for c in _cols.replace("(lo, 6)", "").replace("nullif(n, 0), 1), 6)", "").replace("(rate, 6)", "").replace("round(coalesce(k * 1.0 / ", "").split(", ") if c)):
        return spark.createDataFrame(_bins(spark, sf)[["query_id", *names]])


@key("cal_expected_err", f"{_AT_TAU} SELECT query_id, round(sum(m * rate), 5)::DOUBLE AS expected_errors FROM rate GROUP BY 1")
def cal_expected_err(spark, sf):
    g = _bins(spark, sf).groupby("query_id")["err"].sum().round(5).reset_index().rename(columns={"err": "expected_errors"})
    return spark.createDataFrame(g)


_RETURNED = "SELECT DISTINCT k, n FROM (SELECT CAST(count(*) FILTER (WHERE l_returnflag = 'R') AS INT) AS k, CAST(count(*) AS INT) AS n FROM lineitem GROUP BY l_orderkey // 4)"


def _bounded(spark, sf, columns: str, rates) -> DataFrame:
    """Rates from how many lines were returned and how many there are, over all lots of four orders; equal lots count once."""
    lines = table(spark, sf, "lineitem").groupBy(F.expr("l_orderkey div 4")).agg(F.count_if(F.col("l_returnflag") == "R").cast("int").alias("k"), F.count("*").cast("int").alias("n"))

    def run(parts):
        for p in parts:
            yield pd.DataFrame([(int(k), int(n), *more) for k, n in zip(p["k"], p["n"], strict=True) for more in rates(int(k), int(n))], columns=[c.split()[0] for c in columns.split(", ")])

    return lines.select("k", "n").distinct().mapInPandas(run, columns)


@key("binom_upper", f"WITH RECURSIVE pc AS ({_RETURNED}), {_UPPER.format(d='0.05')} SELECT k, n, round(u, 6)::DOUBLE AS upper FROM ub")
def binom_upper(spark, sf):
    return _bounded(spark, sf, "k int, n int, upper double", lambda k, n: [(round(bounds.binom_upper(k, n), 6),)])


@key("cal_sensitivity", f"WITH RECURSIVE pc AS ({_RETURNED}), {_UPPER.format(d='0.05')} SELECT k, n, w::DOUBLE AS w, round((1 - w) * coalesce(k * 1.0 / nullif(n, 0), 1) + w * u, 6)::DOUBLE AS rate FROM ub, (VALUES (0.0), (0.03), (0.06), (0.25), (1.0)) p(w)")
def cal_sensitivity(spark, sf):
    def rates(k, n):
        return [(w, round(float(bounds.blended(np.array([k]), np.array([n]), w, 0.05)[0]), 6)) for w in (0.0, 0.03, 0.06, 0.25, 1.0)]

    return _bounded(spark, sf, "k int, n int, w double, rate double", rates)


@key("cal_smoothed_band", f"""WITH {_BASE}, g AS (SELECT query_id, i, (SELECT count(*) FROM c WHERE c.query_id = q.query_id AND least(floor(c.prob * 64), 63) = i) AS n, (SELECT coalesce(sum(y), 0) FROM c WHERE c.query_id = q.query_id AND least(floor(c.prob * 64), 63) = i) AS k,
    (SELECT count(*) FROM pool p WHERE p.query_id = q.query_id AND least(floor(p.prob * 64), 63) = i) AS m FROM (SELECT DISTINCT query_id FROM c) q, range(64) r(i)), x AS (SELECT *, (k + 1.0) / (n + 2.0) AS rate FROM g),
    a AS (SELECT q.query_id, p.i AS lo, h.i AS hi, (SELECT coalesce(sum(m * rate), 0) FROM x WHERE x.query_id = q.query_id AND x.i < p.i) + (SELECT coalesce(sum(m * (1 - rate)), 0) FROM x WHERE x.query_id = q.query_id AND x.i >= h.i) AS err,
    (SELECT coalesce(sum(m), 0) FROM x WHERE x.query_id = q.query_id AND x.i >= p.i AND x.i < h.i) AS cascade, (SELECT count(*) FROM s WHERE s.query_id = q.query_id) AS n_all FROM (SELECT DISTINCT query_id FROM c) q, range(65) p(i), range(65) h(i) WHERE h.i >= p.i)
    SELECT query_id, min(cascade)::BIGINT AS cascade FROM a WHERE err <= 0.1 * n_all + 1e-9 GROUP BY 1""")
def cal_smoothed_band(spark, sf):
    b, scores, cal, led = cal_bench(spark, sf)
    got = ms.calibrate(b, scores, cal, led.rows, "smoothed_band")
    return spark.createDataFrame([(q, int(c[2])) for q, c in got.items()], "query_id string, cascade long")


def _omni_sql(alphas=(0.9,)) -> str:
    vals = ", ".join(f"({a}::DOUBLE)" for a in alphas)
    return f"""WITH s AS ({_S}), w AS (SELECT query_id, conf, sum(CASE WHEN y <> yhat THEN 1 ELSE 0 END) OVER p AS err, count(*) OVER p AS acc, count(*) OVER (PARTITION BY query_id) AS n FROM s WINDOW p AS (PARTITION BY query_id ORDER BY conf DESC RANGE UNBOUNDED PRECEDING))
        SELECT query_id, alpha, round(min(conf), 6)::DOUBLE AS tau, CAST(max(n) - max(acc) AS BIGINT) AS cascade FROM w, (VALUES {vals}) a(alpha) WHERE err <= round((1 - alpha) * n, 9) GROUP BY 1, 2"""


def _omni(spark, sf, alphas=(0.9,)) -> DataFrame:
    b = bench(spark, sf, HARD)
    s = ms.prebuilt_scores(b).join(b.answers.select("query_id", "doc_id", "y"), ["query_id", "doc_id"]).withColumn("wrong", (F.col("yhat") != F.col("y")).cast("int"))
    return bayes.omniscient(s, list(alphas))


@key("cal_omniscient", _omni_sql())
def cal_omniscient(spark, sf):
    return _omni(spark, sf).select("query_id", "alpha", F.round("tau", 6).alias("tau"), "cascade")


@key("cal_ks_audit", f"""WITH s AS ({_S}), v AS (SELECT query_id, conf, count(*) FILTER (WHERE part = 'cal') AS a, count(*) FILTER (WHERE part IS DISTINCT FROM 'cal') AS b FROM s GROUP BY 1, 2),
    w AS (SELECT query_id, sum(a) OVER p / sum(a) OVER q - sum(b) OVER p / sum(b) OVER q AS d FROM v WINDOW p AS (PARTITION BY query_id ORDER BY conf), q AS (PARTITION BY query_id)) SELECT query_id, round(max(abs(d)), 6)::DOUBLE AS ks FROM w GROUP BY 1""")
def cal_ks_audit(spark, sf):
    """Largest gap between the score distributions of calibration set and pool, the second assumption."""
    b, scores, cal, _ = cal_bench(spark, sf)
    marked = scores.join(cal.select("query_id", "doc_id", F.lit(1).alias("c")), ["query_id", "doc_id"], "left").groupBy("query_id", "conf").agg(F.count("c").alias("a"), F.count_if(F.col("c").isNull()).alias("b"))
    p, q = W.partitionBy("query_id").orderBy("conf"), W.partitionBy("query_id")
    d = F.sum("a").over(p) / F.sum("a").over(q) - F.sum("b").over(p) / F.sum("b").over(q)
    return marked.select("query_id", F.abs(d).alias("d")).groupBy("query_id").agg(F.round(F.max("d"), 6).alias("ks"))


# ---- methods -------------------------------------------------------------------------------------
_RUN_COLS = ("method", "corpus", "query_id", "alpha", "accuracy", "f1", "n_vote", "n_train", "n_cal", "n_cascade", "n_pilot", "n_oracle", "proxy_s", "oracle_s", "e2e_s", "sla_hit", "sla_gap", "phase2")


_RUN_ROW = "method string, corpus string, query_id string, alpha double, accuracy double, f1 double, n_vote long, n_train long, n_cal long, n_cascade long, n_pilot long, n_oracle long, proxy_s double, oracle_s double, e2e_s double, sla_hit long, sla_gap double, phase2 boolean"


def shown(spark, *results) -> DataFrame:
    if not results:
        return spark.createDataFrame([], _RUN_ROW)
    frame = pd.concat([r.runs for r in results])[list(_RUN_COLS)].round(6)
    return spark.createDataFrame(frame)


@key("method_exhaustive", f"SELECT query_id, count(*) AS n_oracle, 1.0::DOUBLE AS accuracy FROM {truth()} t GROUP BY 1")
def method_exhaustive(spark, sf):
    return spark.createDataFrame(ms.run_exhaustive(bench(spark, sf)).runs[["query_id", "n_oracle", "accuracy"]])


_PRE = f"""WITH t AS ({choice('uniform_margin')}), s2 AS ({_S}) SELECT s2.query_id, count(*) FILTER (WHERE part = 'cal') AS n_cal, count(*) FILTER (WHERE part IS DISTINCT FROM 'cal' AND conf < t.tau - 5e-7) AS n_cascade,
    round(avg(CASE WHEN part = 'cal' OR conf < t.tau - 5e-7 OR y = yhat THEN 1.0 ELSE 0.0 END), 6)::DOUBLE AS accuracy FROM s2 JOIN t USING (query_id) GROUP BY 1"""


@key("method_prebuilt", _PRE)
def method_prebuilt(spark, sf):
    r = ms.run_prebuilt(bench(spark, sf, HARD)).runs[["query_id", "n_cal", "n_cascade", "accuracy"]]
    return spark.createDataFrame(r.assign(accuracy=r["accuracy"].round(6)))


@key("method_floor", f"SELECT query_id, floor_calls AS n_oracle FROM ({_floor_sql((0.9,))})")
def method_floor(spark, sf):
    return spark.createDataFrame(ms.run_floor(bench(spark, sf, HARD)).runs[["query_id", "n_oracle"]])


SMALL = ("Q01", "Q07", "Q19")


@key("method_cluster_vote")
def method_cluster_vote(spark, sf):
    return shown(spark, ms.run_cluster_vote(bench(spark, sf, cat.ALL)))


@key("method_biencoder")
def method_biencoder(spark, sf):
    return shown(spark, ms.run_trained(bench(spark, sf, cat.ALL), "biencoder", "smoothed_histogram"))


@key("method_hybrid")
def method_hybrid(spark, sf):
    return shown(spark, ms.run_trained(bench(spark, sf, cat.ALL)))


@key("method_two_phase")
def method_two_phase(spark, sf):
    return shown(spark, ms.run_two_phase(bench(spark, sf, SMALL)))


@key("method_router")
def method_router(spark, sf):
    return shown(spark, ms.run_router(bench(spark, sf, ("Q01", "Q19"))))


@key("method_ber_router")
def method_ber_router(spark, sf):
    return shown(spark, ms.run_router(bench(spark, sf, ("Q01", "Q19")), "ber", reuse=True))


@key("two_phase_exit")
def two_phase_exit(spark, sf):
    r = shown(spark, ms.run_two_phase(bench(spark, sf, ("Q01", "Q07"))))
    return r.select("query_id", "phase2", "n_vote", "n_train", "n_cal", "n_cascade")


_VOTED = f"SELECT query_id, count(*) AS n, sum(y)::BIGINT AS yes FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY {u('doc_id', chr(39) + ':vote' + chr(39))}, doc_id) AS r FROM {truth()} t) WHERE r <= 40 GROUP BY 1"


@key("two_phase_train_set", _VOTED)
def two_phase_train_set(spark, sf):
    """T of the second phase: every bought label of the first one, none of the propagated."""
    b = bench(spark, sf)
    led = Ledger(b.answers)
    led.request(b.pairs().withColumn("r", F.row_number().over(W.partitionBy("query_id").orderBy(uniform(F.col("doc_id"), ":vote"), "doc_id"))).filter("r <= 40"), "vote")
    return led.reuse(["vote"], "train").groupBy("query_id").agg(F.count("*").alias("n"), F.sum("y").cast("long").alias("yes"))


for _name in ("exhaustive", "cluster_vote", "prebuilt_cascade", "hybrid_cascade", "two_phase"):

    @key(f"sem_filter_{_name}")
    def _sem_filter(spark, sf, name=_name):
        from ..api import sem_filter
        from ..sources.tables import table

        b = bench(spark, sf, ("Q02",))
        scores = b.answers.select("doc_id", "prob") if name == "prebuilt_cascade" else None
        got = sem_filter(table(spark, sf, "documents").select("doc_id", "text"), StoredOracle(b.answers), "written in English", 0.9, name, Config(), "Q02", scores)
        return got.predictions.groupBy("yhat", "origin").count()


# ---- experiments ---------------------------------------------------------------------------------
@key("rq1_rollup", f"SELECT corpus, method, round(avg(e2e_s), 4)::DOUBLE AS mean_e2e_s, round(avg(n_oracle), 4)::DOUBLE AS mean_calls, count(*) FILTER (WHERE accuracy >= alpha) AS hits, round(sum(greatest(0, alpha - accuracy)), 6)::DOUBLE AS violation FROM {RUNS} GROUP BY 1, 2")
def rq1_rollup(spark, sf):
    return metrics.summary(runs(spark), "corpus", "method").select("corpus", "method", F.round("mean_e2e_s", 4).alias("mean_e2e_s"), F.round("mean_calls", 4).alias("mean_calls"), "hits", F.round("violation", 6).alias("violation"))


#: Predicates that each corpus has the columns for: sources of pages bear no number, and of a turn no language is given either.
CORPORA = {
    "documents": cat.ALL, "pages": tuple(q for q in cat.ALL if q != "Q18"), "conversations": tuple(q for q in cat.ALL if q not in ("Q01", "Q02", "Q03", "Q18", "Q19")),
}


@key("rq1_table")
def rq1_table(spark, sf):
    """Every method on every corpus and predicate, several runs at a time; an empty corpus has none."""
    benches = [bench(spark, sf, queries, name) for name, queries in CORPORA.items()]
    with ThreadPoolExecutor(3) as pool:  # of a run only its rows are kept; plans and models go
        frames = list(pool.map(lambda job: job[0](job[1]).runs[list(_RUN_COLS)], [(f, b) for b in benches if b.n for f in ms.METHODS.values()]))
    return metrics.summary(spark.createDataFrame(pd.concat(frames)) if frames else shown(spark), "corpus", "method")


_SQL_METHODS = ("naive", "blend", "uniform_margin", "smoothed_histogram")


@key("rq1_sql_methods", " UNION ALL ".join(f"SELECT '{m}' AS method, query_id, cascade FROM ({choice(m)}) x{i}" for i, m in enumerate(_SQL_METHODS)) + f" UNION ALL SELECT 'omniscient', query_id, cascade FROM ({_omni_sql()}) y UNION ALL SELECT 'bayes_floor', query_id, floor_calls FROM ({_floor_sql((0.9,))}) z UNION ALL SELECT 'exhaustive', query_id, count(*) FROM {truth(HARD)} t GROUP BY 2")
def rq1_sql_methods(spark, sf):
    parts = [chosen(spark, sf, m).select(F.lit(m).alias("method"), "query_id", "cascade") for m in _SQL_METHODS]
    parts.append(_omni(spark, sf).select(F.lit("omniscient").alias("method"), "query_id", "cascade"))
    b = bench(spark, sf, HARD)
    parts.append(bayes.bayes_floor(b.answers, [0.9]).select(F.lit("bayes_floor").alias("method"), "query_id", F.col("floor_calls").alias("cascade")))
    parts.append(b.answers.groupBy("query_id").agg(F.count("*").alias("cascade")).select(F.lit("exhaustive").alias("method"), "query_id", "cascade"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@key("rq2_sweep_sql", choice("blend", ALPHAS))
def rq2_sweep_sql(spark, sf):
    return chosen(spark, sf, "blend", ALPHAS)


@key("rq2_sweep")
def rq2_sweep(spark, sf):
    out = []
    for a in (0.8, 0.9, 0.95):
        b = bench(spark, sf, ("Q19",), alpha=a)
        out += [ms.run_trained(b).runs, ms.run_prebuilt(b, "blend").runs, ms.run_floor(b).runs]
    return metrics.summary(spark.createDataFrame(pd.concat(out)[list(_RUN_COLS)]), "method", "alpha")


@key("sweep_reuse")
def sweep_reuse(spark, sf):
    b = bench(spark, sf, ("Q19",))
    first = ms.run_trained(b)
    again = ms.run_trained(replace(b, cfg=replace(b.cfg, alpha=0.95)), old=first.trace[0], name="hybrid_reused")
    return shown(spark, first, again)


@key("rq3_segments", f"SELECT query_id, round(count(*) FILTER (WHERE purpose = 'vote') * 0.132, 6)::DOUBLE AS vote_s, round(count(*) FILTER (WHERE purpose = 'train') * 0.132, 6)::DOUBLE AS train_s, round(count(*) FILTER (WHERE purpose = 'cal') * 0.132, 6)::DOUBLE AS cal_s, round(count(*) FILTER (WHERE purpose = 'cascade') * 0.132, 6)::DOUBLE AS cascade_s FROM {LEDGER} GROUP BY 1")
def rq3_segments(spark, sf):
    m = metrics.oracle_calls(spark.sql(f"SELECT * FROM {LEDGER}"))
    return m.select("query_id", *[F.round(F.col(f"n_{p}") * 0.132, 6).alias(f"{p}_s") for p in ("vote", "train", "cal", "cascade")])


@key("rq3_segments_live")
def rq3_segments_live(spark, sf):
    r = ms.run_trained(bench(spark, sf, ("Q04", "Q19"))).runs
    r["cascade_share"] = r["n_cascade"] / r["n_oracle"]
    return spark.createDataFrame(r[["method", "query_id", "proxy_s", "n_vote", "n_train", "n_cal", "n_cascade", "cascade_share", "accuracy"]])


@key("rq4_envelope", f"SELECT corpus, query_id, method, round(min(e2e_s) OVER (PARTITION BY corpus, query_id), 4)::DOUBLE AS envelope_s, round(e2e_s / min(e2e_s) OVER (PARTITION BY corpus, query_id), 4)::DOUBLE AS factor, CASE WHEN row_number() OVER (PARTITION BY corpus, query_id ORDER BY e2e_s, method) = 1 THEN 1 ELSE 0 END AS wins FROM {RUNS}")
def rq4_envelope(spark, sf):
    return metrics.envelope(runs(spark)).select("corpus", "query_id", "method", F.round("envelope_s", 4).alias("envelope_s"), F.round("factor", 4).alias("factor"), "wins")


@key("rq5_auc", f"""WITH w AS (SELECT corpus, query_id, any_value(ber) AS ber, CASE WHEN arg_min(method, e2e_s) IN ('cluster_vote', 'two_phase') THEN 1 ELSE 0 END AS win FROM {RUNS} WHERE method <> 'prebuilt_cascade' AND corpus = 'A' GROUP BY 1, 2)
    SELECT a.corpus, round(avg(CASE WHEN a.ber < b.ber THEN 1.0 WHEN a.ber = b.ber THEN 0.5 ELSE 0.0 END), 6)::DOUBLE AS auc FROM w a JOIN w b ON a.corpus = b.corpus WHERE a.win = 1 AND b.win = 0 GROUP BY 1""")
def rq5_auc(spark, sf):
    r = runs(spark).filter("method <> 'prebuilt_cascade' AND corpus = 'A'").groupBy("corpus", "query_id").agg(F.first("ber").alias("ber"), F.min_by("method", "e2e_s").isin("cluster_vote", "two_phase").cast("int").alias("win")).toPandas()
    return spark.createDataFrame([(c, round(bayes.auc(-g["ber"].to_numpy(), g["win"].to_numpy()), 6)) for c, g in r.groupby("corpus") if 0 < g["win"].sum() < len(g)], "corpus string, auc double")


@key("rq5_fit")
def rq5_fit(spark, sf):
    """Where voting wins against Bayes error, on live runs of the two families."""
    qs = ("Q01", "Q03", "Q08", "Q15", "Q19")
    b = bench(spark, sf, qs)
    vote, hybrid = ms.run_cluster_vote(b).runs, ms.run_trained(b).runs
    ber = {r["query_id"]: r["ber"] for r in bayes.query_ber(b.answers).collect()}
    w = pd.DataFrame({"ber": [ber[q] for q in qs], "win": [int(vote.set_index("query_id").loc[q, "e2e_s"] < hybrid.set_index("query_id").loc[q, "e2e_s"]) for q in qs]})
    return spark.createDataFrame(pd.DataFrame([{**bayes.compass(w), "n": len(qs)}]))


CELLS = {
    "full": ("hybrid", {}), "biencoder_soft": ("biencoder_soft", {}), "contrastive_backbones": ("hybrid", {"backbones": "contrastive"}), "hard_labels": ("hybrid", {"backbones": "hard"}),
    "no_coverage": ("hybrid", {"use_cov": False}), "no_dual": ("hybrid", {"use_dual": False}), "biencoder_contrastive": ("biencoder", {}),
}


#: Cells whose head is trained on the same soft backbones as that of the full proxy.
SAME_BACKBONES = ("no_coverage", "no_dual")


def ablation(spark, sf, cells, queries=("Q07", "Q19"), fired=False) -> DataFrame:
    """Runs of the cells, several at a time; cells that differ in their heads only take the backbones of the full proxy, which are trained once.

    With ``fired``, the cells run on the queries that the first phase leaves open, and all on the labels that the second phase has.
    """
    b, start = bench(spark, sf, queries), None
    if fired:
        b, start = ms.fired(b) if b.n else (b, None)
        if start is None:
            return shown(spark)

    def run(cell: str, old: dict | None = None):
        if start is not None and cell in ("full", *SAME_BACKBONES):
            old = start.first
        return ms.run_trained(b, CELLS[cell][0], "blend", cell, CELLS[cell][1], old, start)

    with ThreadPoolExecutor(3) as pool:
        lent = [c for c in cells if c in SAME_BACKBONES and "full" in cells and start is None]
        runs = {c: pool.submit(run, c) for c in cells if c not in lent}
        if lent:
            runs |= {c: pool.submit(run, c, runs["full"].result().trace[0]) for c in lent}
        return shown(spark, *[runs[c].result() for c in cells])


@key("rq6a_proxy")
def rq6a_proxy(spark, sf):
    """All cells on all predicates whose second phase fires, from the same T and C."""
    return metrics.summary(ablation(spark, sf, CELLS, cat.ALL, fired=True), "method")


for _k, _cell in {"abl_biencoder_soft": "biencoder_soft", "abl_contrastive": "contrastive_backbones", "abl_hard": "hard_labels", "abl_no_cov": "no_coverage", "abl_no_dual": "no_dual"}.items():

    @key(_k)
    def _abl(spark, sf, cell=_cell):
        return ablation(spark, sf, (cell,), ("Q19",))


@key("abl_components")
def abl_components(spark, sf):
    b = bench(spark, sf, ("Q19",))
    return shown(spark, *[ms.run_trained(b, k, "blend", k) for k in ("joint", "late", "mean", "hybrid")])


@key("abl_biased_cal")
def abl_biased_cal(spark, sf):
    """Negative control: the first phase's labels reused for calibration."""
    b = bench(spark, sf, ("Q19",))
    biased = ms.run_two_phase(b, cal_source="phase1")
    biased.runs["method"] = "two_phase_biased_cal"
    return shown(spark, ms.run_two_phase(b), biased)


@key("rq6b_calibration", " UNION ALL ".join(f"SELECT '{m}' AS method, round(avg(cascade), 4)::DOUBLE AS mean_cascade, max(cascade) AS max_cascade FROM ({choice(m)}) x{i}" for i, m in enumerate(("blend", "naive", "range_bound", "smoothed_histogram", "uniform_margin"))))
def rq6b_calibration(spark, sf):
    out = None
    for m in ("blend", "naive", "range_bound", "smoothed_histogram", "uniform_margin"):
        part = chosen(spark, sf, m).agg(F.round(F.avg("cascade"), 4).alias("mean_cascade"), F.max("cascade").alias("max_cascade")).select(F.lit(m).alias("method"), "mean_cascade", "max_cascade")
        out = part if out is None else out.unionByName(part)
    return out


@key("stress_duplicates")
def stress_duplicates(spark, sf):
    b = bench(spark, sf, ("Q13", "Q14", "Q20"))
    return shown(spark, ms.run_prebuilt(b, "blend"), ms.run_floor(b))


@key("scale_lineitem_calibrate")
def scale_lineitem_calibrate(spark, sf):
    """Scan, score and count pool ranges with rows as documents: the part of a plan that touches everything."""
    from ..sources.tables import table

    rows = table(spark, sf, "lineitem").select(F.concat_ws(" ", "l_returnflag", "l_linestatus", F.col("l_quantity").cast("string"), F.col("l_extendedprice").cast("string")).alias("text"), "l_orderkey", "l_linenumber")
    prob = F.pmod(F.xxhash64("text"), F.lit(1_000_003)) / 1_000_003.0
    pool = rows.select(F.lit("Q").alias("query_id"), F.round(F.abs(prob - 0.5) * 2, 9).alias("conf"))
    cuts = {"Q": np.linspace(0, 1, 201)}
    counts = th.pool_counts(pool, cuts)["Q"]
    return spark.createDataFrame([(int(i), int(n)) for i, n in enumerate(counts)], "bucket int, n long")


@key("rq1_corpora")
def rq1_corpora(spark, sf):
    """The deployable cascades on the two other text corpora."""
    out = []
    for name in ("pages", "conversations"):
        b = ms.Bench.documents(spark, sf, ("Q06", "Q17"), Config(), name)
        out += [ms.run_prebuilt(b), ms.run_trained(b), ms.run_two_phase(b)]
    return shown(spark, *out)


@key("stress_vectors")
def stress_vectors(spark, sf):
    """Vectors alone: a predicate that they carry, and one that they do not."""
    b = ms.Bench.vectors(spark, sf)
    return shown(spark, ms.run_trained(b), ms.run_trained(b, "biencoder", "smoothed_histogram"))


@key("cal_split")
def cal_split(spark, sf):
    """Calibration on the half of C that the constraint did not see, beside the default."""
    b = bench(spark, sf, ("Q19",))
    split = ms.run_trained(replace(b, cfg=replace(b.cfg, split_cal=True)), name="hybrid_split_cal")
    return shown(spark, ms.run_trained(b), split)


@key("vote_error_bound")
def vote_error_bound(spark, sf):
    """Share of wrong majorities among propagated documents of each query, to be held against 1 - alpha."""
    b = bench(spark, sf, ("Q01", "Q03"))
    r = ms.run_cluster_vote(b)
    j = r.predictions.filter("origin = 'propagated'").join(b.answers, ["query_id", "doc_id"])
    return j.groupBy("query_id").agg(F.count("*").alias("n"), F.round(F.avg((F.col("yhat") != F.col("y")).cast("double")), 6).alias("error"))
