"""Experiments run over every predicate of every corpus."""

import pickle

import pytest

from semfilter import features
from semfilter.cascades import methods as ms
from semfilter.plans import calibration_queries as plans
from semfilter.plans import catalog
from semfilter.proxy import nets
from semfilter.sources import catalogue as cat
from semfilter.sources.tables import corpus

QUERIES = catalog.queries()


def test_efficiency_table_has_all_corpora_and_predicates(spark, sf, monkeypatch):
    monkeypatch.setattr(ms, "METHODS", {"exhaustive": ms.run_exhaustive, "bayes_floor": ms.run_floor})
    got = {(r["corpus"], r["method"]): r for r in QUERIES["rq1_table"](spark, sf).collect()}
    n = {name: corpus(spark, sf, name).count() for name in ("documents", "pages", "conversations")}
    assert {k: r["n_queries"] for k, r in got.items()} == {(name, m): k for name, k in (("documents", 20), ("pages", 19), ("conversations", 15)) for m in ms.METHODS}
    assert all(got[name, "exhaustive"]["mean_calls"] == n[name] and got[name, "exhaustive"]["min_accuracy"] == 1 for name in n)


@pytest.mark.parametrize("empty", [("pages",), ("documents", "pages", "conversations")])
def test_efficiency_table_without_rows(spark, sf, tmp_path, monkeypatch, empty):
    monkeypatch.setattr(ms, "METHODS", {"exhaustive": ms.run_exhaustive})
    for name in ("documents", "pages", "conversations", "benchmark"):
        t = spark.read.parquet(f"{sf}/{name}.parquet")
        (t.limit(0) if name in empty else t).write.parquet(f"{tmp_path}/{name}.parquet")
    got = QUERIES["rq1_table"](spark, str(tmp_path))
    assert sorted(r["corpus"] for r in got.collect()) == sorted({"documents", "pages", "conversations"} - set(empty))
    assert "n_queries" in got.columns


def test_proxy_ablation_has_all_queries_whose_second_phase_fires(spark, sf, monkeypatch):
    monkeypatch.setattr(plans, "CELLS", {k: plans.CELLS[k] for k in ("full", "hard_labels")})
    runs = ms.run_two_phase(ms.Bench.documents(spark, sf, cat.ALL)).runs.round(6)
    done, want = (runs[runs["phase2"] == f].set_index("query_id") for f in (False, True))
    kept = ["n_vote", "n_cal", "n_cascade", "accuracy"]
    got = plans.ablation(spark, sf, tuple(plans.CELLS), cat.ALL, fired=True).toPandas().set_index("query_id")
    full, hard = (got[got["method"] == m] for m in plans.CELLS)
    assert 1 < len(want) < 20 and full[kept].to_dict() == want[kept].to_dict() and hard[kept[:2]].to_dict() == want[kept[:2]].to_dict()
    assert {r["method"]: r["n_queries"] for r in QUERIES["rq6a_proxy"](spark, sf).collect()} == dict.fromkeys(plans.CELLS, len(want))
    assert plans.ablation(spark, sf, ("full",), tuple(done.index), fired=True).count() == 0


def test_proxy_ablation_without_documents(spark, sf, tmp_path):
    spark.read.parquet(f"{sf}/documents.parquet").limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert QUERIES["rq6a_proxy"](spark, str(tmp_path)).collect() == []


def test_late_scorers_travel_without_their_token_vectors():
    made, whole = nets.LateScorer.seeded([3, 5], 64, 16, 42), nets.LateScorer([3, 5], features.token_table(64, 42).astype(float), 16, 42)
    sent = pickle.dumps(made)
    assert len(sent) < 1 << 15 < len(pickle.dumps(whole))
    toks = [[1, 5], [], [4095]]
    for m in (made, pickle.loads(sent), pickle.loads(pickle.dumps(whole))):
        assert m.prob(None, None, toks).tolist() == whole.prob(None, None, toks).tolist()
