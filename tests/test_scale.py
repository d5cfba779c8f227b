"""What would not hold on large tables: frames on the driver, and queries that read no table."""

import tracemalloc

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.errors import AnalysisException

from semfilter import metrics
from semfilter.config import Config
from semfilter.plans import calibration_queries, catalog
from semfilter.proxy import nets
from semfilter.proxy import train as px

QUERIES, TWINS = catalog.queries(), catalog.twins()


def forbid_frames(spark, monkeypatch):
    def no(*_):
        raise AssertionError("a frame came to the driver")

    monkeypatch.setattr(type(spark.range(1)), "toPandas", no)


def test_hashed_vectors_of_all_documents(spark, sf):
    got = QUERIES["feat_hashed_vector"](spark, sf).collect()
    assert len(got) == 200 and all(r["norm2"] == 1 and r["n_toks"] > 0 for r in got)


@pytest.mark.parametrize("name", ["loss_coverage", "loss_hard", "loss_sla_penalty", "loss_soft", "risk_soft", "loss_total"])
def test_losses_bring_no_documents_to_the_driver(spark, sf, monkeypatch, name):
    forbid_frames(spark, monkeypatch)
    assert QUERIES[name](spark, sf).count() == 4


def test_loss_sums_are_those_of_the_scorers(spark):
    rows = [("a", 0.9, 0.8, 1), ("a", 0.2, 0.4, 1), ("a", 0.0, 0.1, 0), ("b", 0.5, None, 1)]
    got = {r["query_id"]: r for r in metrics.loss_sums(spark.createDataFrame(rows, "query_id string, prob double, p_star double, y int")).collect()}
    p, t, y = (pd.DataFrame(rows[:3])[k].to_numpy(float) for k in (1, 2, 3))
    a, b = got["a"], got["b"]
    assert a["soft"] / a["n_soft"] == pytest.approx(nets.bce(p, t)) and a["hard"] / a["n"] == pytest.approx(nets.bce(p, y))
    assert 1 - a["conf"] / a["n"] == pytest.approx(nets.coverage_loss(p)) and nets.soft_risk_of(a["wrong"], a["conf"]) == pytest.approx(nets.soft_risk(p, y))
    assert (b["n"], b["n_soft"], b["soft"], b["conf"]) == (1, 0, None, 0)


def test_pairs_of_a_margin_loss_are_not_made():
    rng = np.random.default_rng(0)
    for pos, neg in ((rng.normal(size=7), rng.normal(size=11)), (np.zeros(3), np.full(2, -0.4)), (np.array([0.1]), np.array([0.9]))):
        gap = 0.4 - pos[:, None] + neg[None, :]
        loss, of_pos, of_neg = nets.pair_hinge(pos, neg, 0.4)
        assert loss == pytest.approx(np.maximum(gap, 0).mean())
        assert of_pos.tolist() == (gap > 0).mean(axis=1).tolist() and of_neg.tolist() == (gap > 0).mean(axis=0).tolist()


def test_contrastive_training_takes_room_for_its_documents_only():
    n, rng = 8000, np.random.default_rng(0)
    emb, y, q = rng.normal(size=(n, 4)), np.arange(n) % 2, rng.normal(size=4)
    tracemalloc.start()
    nets.BiEncoder(4).contrast(q, emb, y, 1, 1e-3, 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60 << 20  # the pairs alone took 16 million doubles


def test_global_top_is_by_the_rounded_value(spark, tmp_path):
    rows = ", ".join(f"({i}, 'a b', 'en', 'src1', {10**6 * (i + 1)})" for i in range(30))
    con = duckdb.connect()
    con.execute(f"COPY (SELECT i::BIGINT AS doc_id, t AS text, l AS lang, s AS source, n::BIGINT AS n_chars FROM (VALUES {rows}) v(i, t, l, s, n)) TO '{tmp_path}/documents.parquet'")
    con.execute(f"COPY (SELECT 0::BIGINT AS item_id, 'none' AS text) TO '{tmp_path}/benchmark.parquet'")
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet'")
    want = con.execute(TWINS["topk_global"]).fetchall()
    got = [tuple(r) for r in QUERIES["topk_global"](spark, str(tmp_path)).collect()]
    assert got == want and len({p for _, p in want}) < len(want)


def test_contrastive_training_of_a_joint_scorer_goes_by_parts(monkeypatch):
    rng = np.random.default_rng(0)
    emb, y, q, seen = rng.normal(size=(50, 4)), (np.arange(50) % 3 == 0).astype(int), rng.normal(size=4), []
    whole = nets.JointScorer(4, 3)
    nets.fit_contrastive(whole, q, emb, [[]] * 50, y, 3, Config())
    monkeypatch.setattr(nets, "ROWS", 16)
    before = nets.joint_input
    monkeypatch.setattr(nets, "joint_input", lambda a, d: seen.append(len(d)) or before(a, d))
    parts = nets.JointScorer(4, 3)
    nets.fit_contrastive(parts, q, emb, [[]] * 50, y, 3, Config())
    assert max(seen) == 16 and all(np.allclose(a, b) for a, b in zip(whole.params, parts.params, strict=True))
    assert len(parts.prob(q, emb[:0])) == 0


def test_ablation_trains_the_backbones_of_equal_cells_once(spark, sf, monkeypatch):
    lent, train_all = [], px.train_all
    monkeypatch.setattr(px, "train_all", lambda labelled, kind, asks, cfg, old=None, **flags: lent.append(old is not None) or train_all(labelled, kind, asks, cfg, old, **flags))
    got = {r["method"]: r for r in calibration_queries.ablation(spark, sf, ("full", "no_dual"), ("Q19",)).collect()}
    assert sorted(lent) == [False, True]
    assert got["no_dual"] == calibration_queries.ablation(spark, sf, ("no_dual",), ("Q19",)).first()


@pytest.mark.parametrize("name", ["acc_mean_min", "agg_bool", "agg_filter_clause", "agg_min_max_by", "agg_pivot", "agg_unpivot", "ber_buckets", "biencoder_forward", "binom_upper", "cal_sensitivity", "compass_auc", "compass_crossover"])
def test_made_up_inputs_gave_way_to_tables(spark, name):
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, "/no/such/folder").collect()
