"""Worked examples: answers that follow by hand."""

import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from semfilter import bayes
from semfilter import features as feat
from semfilter.calibrate import bounds
from semfilter.calibrate import threshold as th
from semfilter.config import Config
from semfilter.proxy import nets

FLOOR_P = [0.99, 0.98, 0.9, 0.8, 0.7, 0.6, 0.5, 0.5, 0.95, 0.97]


@pytest.mark.parametrize(("k", "n", "want"), [(0, 20, 0.139108), (1, 20, 0.216106), (0, 25, 0.112928), (1, 25, 0.176121), (2, 25, 0.231040), (3, 25, 0.281723), (0, 1, 0.95), (2, 500, 0.012538), (25, 25, 1)])
def test_binom_upper(k, n, want):
    assert bounds.binom_upper(k, n) == pytest.approx(want, abs=1e-6)


@pytest.mark.parametrize(("k", "n", "want"), [(0, 20, 0.008347), (1, 20, 0.059966), (2, 25, 0.089062), (3, 25, 0.129703), (2, 500, 0.004512)])
def test_blend(k, n, want):
    assert bounds.blended(np.array([k]), np.array([n]), 0.06, 0.05)[0] == pytest.approx(want, abs=1e-6)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 120), st.data())
def test_bound_is_monotone_and_above_the_rate(n, data):
    k = data.draw(st.integers(0, n))
    u = bounds.binom_upper(k, n)
    assert u >= k / n
    assert k == n or bounds.binom_upper(k + 1, n) >= u - 1e-12
    assert bounds.binom_upper(k, n + 1) <= u + 1e-12
    b = bounds.blended(np.array([k]), np.array([n]), 0.06, 0.05)[0]
    assert k / n - 1e-12 <= b <= u + 1e-12
    assert bounds.hoeffding_upper(k, n) >= k / n


def test_bound_covers():
    rng = np.random.default_rng(1)
    for p, n in ((0.05, 40), (0.2, 25), (0.01, 100)):
        k = rng.binomial(n, p, 3000)
        assert np.mean([bounds.binom_upper(x, n) >= p for x in k]) >= 0.94


def test_floor_by_hand(spark):
    rows = [("Q", i, p, int(p >= 0.5)) for i, p in enumerate(FLOOR_P)] + [("Z", i, 0.95, 1) for i in range(10)]
    got = {r["query_id"]: r["floor_calls"] for r in bayes.bayes_floor(spark.createDataFrame(rows, "query_id string, doc_id int, p_star double, y int"), [0.9]).collect()}
    assert got == {"Q": 3, "Z": 0}


@settings(max_examples=15, deadline=None)
@given(st.lists(st.sampled_from([0.5, 0.6, 0.7, 0.75, 0.8, 0.9, 0.99, 1.0]), min_size=1, max_size=9), st.sampled_from([0.7, 0.8, 0.9, 0.95]))
def test_floor_is_the_best_subset(spark, ps, alpha):
    e = [min(p, 1 - p) for p in ps]
    most = max(r for r in range(len(ps) + 1) for s in itertools.combinations(e, r) if sum(s) <= (1 - alpha) * len(ps) + 1e-9)
    df = spark.createDataFrame([("Q", i, p) for i, p in enumerate(ps)], "query_id string, doc_id int, p_star double")
    r = bayes.bayes_floor(df, [alpha]).first()
    assert r["floor_calls"] == len(ps) - most
    assert (r["floor_calls"] == 0) == (sum(e) <= (1 - alpha) * len(ps) + 1e-9)


def test_floor_falls_with_the_target(spark):
    df = spark.createDataFrame([("Q", i, p) for i, p in enumerate(FLOOR_P)], "query_id string, doc_id int, p_star double")
    calls = [r["floor_calls"] for r in bayes.bayes_floor(df, [0.7, 0.8, 0.9, 0.95]).orderBy("alpha").collect()]
    assert calls == sorted(calls)


def test_vote_size():
    assert [Config().vote_size(n) for n in (1000, 10_000, 50_000)] == [100, 100, 250]
    assert Config().scaled(1000).vote_size(1000) == 10 and Config().scaled(10_000).vote_size(10_000) == 100


def test_scores_and_losses():
    assert nets.confidence(np.array([0.5, 0.9, 0.1, 1.0])).tolist() == pytest.approx([0, 0.8, 0.8, 1])
    assert nets.head_features(np.array([0.6]), np.array([0.2]))[0].tolist() == pytest.approx([0.6, 0.2, 0.12, 0.4, 0.36, 0.04])
    q, d = np.eye(2), np.array([[0.8, 0.6], [0.0, 1.0]])
    assert nets.maxsim(q, d) == pytest.approx(1.8) == nets.maxsim(q, np.vstack([d, d[::-1]]))
    assert nets.bce(np.array([0.5]), np.array([0.5])) == pytest.approx(0.693147, abs=1e-6)
    assert nets.soft_risk(np.array([0.9, 0.2]), np.array([1, 1]), 0) == pytest.approx(0.4)
    assert nets.sla_penalty(0.4, 0.9, 0.5) == pytest.approx(0.15)
    assert nets.dual_step(0.01, 0.4, 0.1) == pytest.approx(0.16) and nets.dual_step(0.01, 0.05, 0.1) == 0
    assert nets.coverage_loss(np.array([0.9, 0.2])) == pytest.approx(0.3)
    assert nets.total_loss(0.4, 0.3, 0.15) == pytest.approx(0.655)


def test_undecided_scores_meet_the_constraint_but_cost_coverage():
    p, y = np.full(10, 0.5), np.ones(10)
    assert nets.soft_risk(p, y) == 0 and nets.coverage_loss(p) == 1


def test_head_size():
    assert nets.HybridHead().net.count() == 1313


def numeric(f, x, eps=1e-6):
    g = np.zeros_like(x)
    for i in np.ndindex(x.shape):
        x[i] += eps
        a = f()
        x[i] -= 2 * eps
        g[i] = (a - f()) / (2 * eps)
        x[i] += eps
    return g


@pytest.mark.parametrize("kind", ["joint", "late"])
def test_gradients(kind):
    rng = np.random.default_rng(0)
    emb, target, q = rng.normal(size=(5, 4)), rng.random(5), rng.normal(size=4)
    toks = [[1, 2], [3], [0, 4, 5], [], [2]]
    m = nets.JointScorer(4, 3, 1) if kind == "joint" else nets.LateScorer([1, 2], rng.normal(size=(6, 4)), 3, 1, free=2)
    grads = m.grad(q, emb, toks, target)
    for p, g in zip(m.params, grads, strict=True):
        assert np.allclose(g, numeric(lambda: nets.bce(m.prob(q, emb, toks), target), p), atol=1e-5)


def test_every_token_of_a_long_text_is_scored(monkeypatch):
    rng = np.random.default_rng(0)
    words = [f"{a}{b}" for a in "abcdefghijklmnopqrst" for b in "abcdefghijklmnopqrst"]
    long = feat.token_ids(" ".join(words))
    assert {i for w in words for i in feat.token_ids(w)} == set(long) and len(long) > 300
    m = nets.LateScorer(feat.token_ids(words[7]), feat.token_table(8), 3, 1)
    toks = [long, [], feat.token_ids(words[7]), *(sorted(rng.choice(4096, n, replace=False).tolist()) for n in (900, 5, 60))]
    want = [nets.maxsim(m._queries() @ m.proj, m.table[t] @ m.proj) if t else 0.0 for t in toks]
    for most in (1, 400, 1 << 18):
        monkeypatch.setattr(nets, "TOKENS", most)
        assert np.allclose(m._score(toks), want, atol=1e-4)


def test_bi_encoder_gradient():
    rng = np.random.default_rng(0)
    emb, y, q = rng.normal(size=(6, 4)), np.array([1, 0, 1, 0, 1, 0.0]), rng.normal(size=4)
    m = nets.BiEncoder(4, 3, 2)
    keep = []
    cos = m.cosine(q, emb, keep)
    g = (nets.sigmoid(4 * cos) - y) / len(y) * 4
    for p, got in zip([*m.q.params, *m.d.params], m._pull(keep, g), strict=True):
        assert np.allclose(got, numeric(lambda: nets.bce(nets.sigmoid(4 * m.cosine(q, emb)), y), p), atol=1e-5)


def test_expected_errors_by_hand():
    cfg = Config(alpha=0.9, n_candidates=2, blend=0.0)
    conf, wrong = np.array([0.2, 0.4, 0.6, 0.8]), np.array([1, 0, 0, 0])
    cuts = th.cut_points(conf, cfg)
    pool = np.array([0.1, 0.2, 0.3, 0.5, 0.7, 0.9] * 10)
    counts = np.bincount(np.searchsorted(cuts, pool, side="right"), minlength=len(cuts) + 1)
    c = th.select_tau(conf, wrong, cuts, counts, len(pool), cfg, "naive")
    assert c.tau == 0.5 and c.cascade == 30


def test_thresholds_are_the_best_of_all():
    rng = np.random.default_rng(4)
    cfg = Config(alpha=0.9, n_candidates=30)
    for _ in range(10):
        conf = np.round(rng.random(60), 2)
        wrong = (rng.random(60) < 0.4 * (1 - conf)).astype(int)
        pool = np.round(rng.random(500), 2)
        cuts = th.cut_points(conf, cfg)
        counts = np.bincount(np.searchsorted(cuts, pool, side="right"), minlength=len(cuts) + 1)
        for method in ("blend", "naive", "range_bound", "uniform_margin", "hoeffding", "smoothed_histogram"):
            got = th.select_tau(conf, wrong, cuts, counts, 500, cfg, method)
            best = math.inf
            for tau in th.candidates(conf, cfg.n_candidates):
                if method in ("uniform_margin", "hoeffding"):
                    lo = np.array([tau])
                elif method == "smoothed_histogram":
                    lo = np.unique(np.append(np.arange(64)[np.arange(64) / 64 > tau] / 64, tau))
                else:
                    lo = th.edges_for(conf, tau, cfg)
                hi = np.append(lo[1:], 9)
                k = np.array([wrong[(conf >= a) & (conf < b)].sum() for a, b in zip(lo, hi, strict=True)])
                n = np.array([((conf >= a) & (conf < b)).sum() for a, b in zip(lo, hi, strict=True)])
                m = np.array([((pool >= a) & (pool < b)).sum() for a, b in zip(lo, hi, strict=True)])
                if (m * th.rates(k, n, method, cfg))[m > 0].sum() <= 0.1 * 500 + 1e-9:
                    best = min(best, 500 - m.sum())
            assert min(got.cascade, 500) == min(best, 500)
        t = [th.select_tau(conf, wrong, cuts, counts, 500, cfg, m).cascade for m in ("naive", "blend", "range_bound")]
        assert t == sorted(t)


def test_omniscient_by_hand(spark):
    df = spark.createDataFrame([("Q", i, c, w) for i, (c, w) in enumerate(zip([0.9, 0.8, 0.7, 0.6, 0.5], [0, 0, 1, 0, 1], strict=True))], "query_id string, doc_id int, conf double, wrong int")
    r = bayes.omniscient(df, [0.8]).first()
    assert (r["tau"], r["cascade"], r["errors"]) == (0.6, 1, 1)


def test_compass():
    ber, win = np.array([0.01, 0.02, 0.06, 0.03, 0.08, 0.10]), np.array([1, 1, 1, 0, 0, 0])
    assert bayes.auc(-ber, win) == pytest.approx(8 / 9)
    a, b = bayes.logistic(ber, win)
    assert b < 0 and 0.02 < -a / b < 0.09


def test_edges_keep_ties_together():
    e = th.equal_freq_edges(np.array([0.1] * 10 + [0.2] * 5), 5)
    assert e.tolist() == [0.1, 0.2]
    assert len(th.equal_freq_edges(np.arange(100) / 100, 20)) == 20 and len(th.equal_freq_edges(np.empty(0), 20)) == 0
