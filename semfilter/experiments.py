"""Runs the published experiments on the given tables and prints their tables.

    python -m semfilter.experiments --sf /root/testdata/sf0.1 --out results.json
"""

from __future__ import annotations

import argparse
import json
import time
from dataclasses import replace

import pandas as pd
from pyspark.sql import SparkSession

from . import bayes
from .cascades import methods as ms
from .config import Config
from .plans.calibration_queries import CELLS
from .sources import catalogue as cat

#: Predicates that need nothing but the text, for the corpora without language and source.
TEXT = ("Q04", "Q05", "Q06", "Q07", "Q08", "Q09", "Q10", "Q11", "Q12", "Q15", "Q16", "Q17", "Q20")
CORPORA = {"documents": cat.ALL, "pages": TEXT, "conversations": TEXT}


def rollup(runs: pd.DataFrame, by: list[str]) -> pd.DataFrame:
    g = runs.groupby(by)
    return pd.DataFrame({"queries": g.size(), "mean_e2e_s": g["e2e_s"].mean(), "mean_calls": g["n_oracle"].mean(), "hits": g["sla_hit"].sum(), "violation": g["sla_gap"].sum(), "mean_acc": g["accuracy"].mean(), "min_acc": g["accuracy"].min(), "mean_f1": g["f1"].mean()}).round(4).reset_index()


def rq1(spark, sf: str, corpora=CORPORA) -> pd.DataFrame:
    """Every method on every corpus at target 0.9."""
    out = []
    for name, queries in corpora.items():
        b = ms.Bench.documents(spark, sf, queries, Config(), name)
        ber = {r["query_id"]: r["ber"] for r in bayes.query_ber(b.answers).collect()}
        for method, run in ms.METHODS.items():
            began = time.time()
            runs = run(b).runs
            runs["ber"], runs["stage_s"] = runs["query_id"].map(ber), time.time() - began
            out.append(runs)
            print(f"# {name} {method}: {time.time() - began:.1f} s", flush=True)
    return pd.concat(out)


def rq2(spark, sf: str, queries=("Q04", "Q07", "Q15", "Q17", "Q19"), alphas=(0.7, 0.8, 0.9, 0.95)) -> pd.DataFrame:
    """Cost against target accuracy; backbones are trained once."""
    b, out = ms.Bench.documents(spark, sf, queries), []
    first = ms.run_trained(b)
    for a in alphas:
        at = replace(b, cfg=replace(b.cfg, alpha=a))
        out += [ms.run_trained(at, old=first.trace[0]).runs, ms.run_prebuilt(at).runs, ms.run_two_phase(at).runs, ms.run_floor(at).runs]
    return pd.concat(out)


def rq4(runs: pd.DataFrame) -> pd.DataFrame:
    """How often each deployable method is the cheapest of its query, and how far above that it is otherwise."""
    live = runs[~runs["method"].isin(["bayes_floor", "exhaustive"])].copy()
    low = live.groupby(["corpus", "query_id"])["e2e_s"].transform("min")
    live["factor"], live["wins"] = live["e2e_s"] / low.clip(lower=1e-9), live["e2e_s"] <= low
    return live.groupby(["corpus", "method"]).agg(wins=("wins", "sum"), median_factor=("factor", "median"), worst_factor=("factor", "max")).round(3).reset_index()


def rq5(runs: pd.DataFrame) -> pd.DataFrame:
    """Compass: does Bayes error tell where voting beats the trained cascade?"""
    wide = runs.pivot_table(index=["corpus", "query_id", "ber"], columns="method", values="e2e_s").reset_index()
    wide["win"] = (wide["cluster_vote"] < wide["hybrid_cascade"]).astype(int)
    return pd.DataFrame([{"corpus": c, **bayes.compass(g)} for c, g in wide.groupby("corpus")]).round(4)


def rq6(spark, sf: str, queries=("Q04", "Q07", "Q15", "Q17", "Q19")) -> tuple[pd.DataFrame, pd.DataFrame]:
    """Ablations: proxy cells under the blended calibration, and calibrations under the full proxy."""
    b = ms.Bench.documents(spark, sf, queries)
    cells = [ms.run_trained(b, kind, "blend", name, flags) for name, (kind, flags) in CELLS.items()]
    full = cells[0].trace[0]
    cal = [ms.run_trained(b, "hybrid", m, m, old=full) for m in ("blend", "naive", "smoothed_histogram", "smoothed_band", "range_bound", "uniform_margin")]
    return rollup(pd.concat([c.runs for c in cells]), ["method"]), rollup(pd.concat([c.runs for c in cal]), ["method"])


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("--sf", default="/root/testdata/sf0.1")
    p.add_argument("--out")
    p.add_argument("--cpus", default="8")
    p.add_argument("--parts", default="rq1,rq2,rq6")
    p.add_argument("--corpora", default=",".join(CORPORA))
    a = p.parse_args()
    spark = SparkSession.builder.master(f"local[{a.cpus}]").config("spark.sql.shuffle.partitions", a.cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "12g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    tables: dict[str, pd.DataFrame] = {}
    if "rq1" in a.parts:
        runs = rq1(spark, a.sf, {k: v for k, v in CORPORA.items() if k in a.corpora.split(',')})
        segments = runs.groupby(["corpus", "method"])[["proxy_s", "n_vote", "n_train", "n_cal", "n_cascade"]].mean().round(2).reset_index()
        tables |= {"rq1": rollup(runs, ["corpus", "method"]), "rq3_segments": segments, "rq4_envelope": rq4(runs), "rq5_compass": rq5(runs)}
        tables["rq1_queries"] = runs.pivot_table(index=["corpus", "query_id", "ber"], columns="method", values="n_oracle").round(4).reset_index()
    if "rq2" in a.parts:
        tables["rq2"] = rollup(rq2(spark, a.sf), ["method", "alpha"])
    if "rq6" in a.parts:
        tables["rq6a_proxy"], tables["rq6b_calibration"] = rq6(spark, a.sf)
    for name, t in tables.items():
        print(f"\n## {name}\n{t.to_string(index=False)}", flush=True)
    if a.out:
        with open(a.out, "w") as f:
            json.dump({k: json.loads(t.to_json(orient="records")) for k, t in tables.items()}, f, indent=1)
    spark.stop()


if __name__ == "__main__":
    main()
