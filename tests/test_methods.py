"""Invariants of the methods on the small corpus."""

import os
import uuid
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from semfilter import clustering, sampling
from semfilter.api import sem_filter
from semfilter.cascades import methods as ms
from semfilter.config import Config
from semfilter.oracle import CallableOracle, Ledger, StoredOracle


@pytest.fixture(scope="module")
def bench(spark, sf01):
    return ms.Bench.documents(spark, sf01, ("Q01", "Q19"))


def holds(b, r):
    keys = ["query_id", "doc_id"]
    assert r.predictions.count() == b.n * len(b.queries)
    assert r.predictions.filter("yhat IS NULL").count() == 0
    assert r.ledger.count() == r.ledger.select(*keys).distinct().count()
    own = r.predictions.filter("origin = 'oracle'").join(b.answers, keys)
    assert own.filter("yhat <> y").count() == 0
    paid = r.runs.set_index("query_id")["n_oracle"].to_dict()
    assert paid == {**dict.fromkeys(b.queries, 0), **{x["query_id"]: x["count"] for x in r.ledger.groupBy("query_id").count().collect()}}


def test_exhaustive_and_floor(bench):
    r = ms.run_exhaustive(bench)
    holds(bench, r)
    assert (r.runs["accuracy"] == 1).all() and (r.runs["n_oracle"] == bench.n).all()
    f = ms.run_floor(bench)
    holds(bench, f)
    assert (f.runs["n_oracle"] <= r.runs["n_oracle"]).all()


def test_hybrid(bench):
    r = ms.run_trained(bench)
    holds(bench, r)
    t, c = (r.ledger.filter(F.col("purpose") == p).select("query_id", "doc_id") for p in ("train", "cal"))
    assert t.intersect(c).count() == 0
    again = ms.run_trained(bench)
    assert again.runs["n_cascade"].tolist() == r.runs["n_cascade"].tolist()
    assert all(0 <= d <= 10 for d in r.trace[0]["Q19"].parts["dual_trace"])


def test_two_phase(bench):
    r = ms.run_two_phase(bench)
    holds(bench, r)
    easy = r.runs.set_index("query_id").loc["Q01"]
    assert not easy["phase2"] and easy["n_train"] == easy["n_cal"] == easy["n_cascade"] == 0
    hard = r.runs.set_index("query_id").loc["Q19"]
    assert hard["phase2"] and hard["n_vote"] <= 0.07 * bench.n + bench.cfg.vote_size(bench.n)


def test_vote_runs_to_the_end(bench):
    b = replace(bench, queries=("Q01",), answers=bench.answers.filter("query_id = 'Q01'"))
    r = ms.run_cluster_vote(b)
    holds(b, r)
    assert r.runs["accuracy"][0] >= 0.9


def test_calibrations_are_ordered(bench):
    n = {m: ms.run_prebuilt(bench, m).runs.set_index("query_id")["n_cascade"] for m in ("naive", "blend", "range_bound")}
    assert (n["naive"] <= n["blend"]).all() and (n["blend"] <= n["range_bound"]).all()


def test_ledger_never_pays_twice(bench):
    led = Ledger(bench.answers)
    some = bench.answers.filter("doc_id < 20")
    assert led.request(some, "train").count() == 40 and led.request(some.union(some), "cal").count() == 0
    assert led.rows.count() == 40


def test_samples_do_not_depend_on_partitions(bench):
    pairs = bench.pairs()
    want = None
    for n in (1, 4, 17):
        got = sorted(map(tuple, sampling.split_sample(pairs.repartition(n), 0.07, 0.05).filter("part IS NOT NULL").collect()))
        assert want in (None, got)
        want = got
    s = sampling.stratified_sample(ms.prebuilt_scores(bench), 0.1, 5).groupBy("query_id", "stratum").count().collect()
    assert {r["count"] for r in s} == {20}


def test_filter_operator(spark, sf01, bench):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    got = sem_filter(docs.select("doc_id", "text"), StoredOracle(bench.answers), "written in German", 0.9, "two_phase", Config(), "Q01")
    kept = got.accepted(docs)
    assert kept.columns == docs.columns and kept.filter("lang = 'de'").count() >= 0.9 * docs.filter("lang = 'de'").count()
    assert "threshold" in got.explain()


def counted(folder):
    """An oracle that leaves a line for every text that it is asked about."""

    def ask(texts):
        with open(f"{folder}/{uuid.uuid4().hex}", "w") as f:
            f.write("\n".join(str(hash(t)) for t in texts))
        return [0.95 if " the " in t else 0.05 for t in texts]

    return ask


def calls(folder):
    return sum(len(open(f"{folder}/{f}").read().split("\n")) for f in os.listdir(folder))


@pytest.mark.parametrize("method", ["exhaustive", "cluster_vote", "biencoder_cascade", "hybrid_cascade", "two_phase", "prebuilt_cascade"])
def test_oracle_is_asked_for_the_ledger_only(spark, sf01, tmp_path, method):
    docs = spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text", "lang")
    scores = docs.selectExpr("doc_id", "if(instr(text, ' the ') > 0, 0.99D, 0.01D) AS prob") if method == "prebuilt_cascade" else None
    got = sem_filter(docs, counted(tmp_path), "uses the article", 0.9, method, Config(epochs_joint=5, epochs_late=2, epochs_head=10), scores=scores)
    asked, n = calls(tmp_path), docs.count()
    assert asked == got.detail.ledger.count() == got.run["n_oracle"] and (asked == n if method == "exhaustive" else 0 < asked < n)
    assert got.predictions.count() == n and got.predictions.filter("yhat IS NULL").count() == 0


@pytest.mark.parametrize("method", ["exhaustive", "cluster_vote", "hybrid_cascade", "two_phase", "prebuilt_cascade"])
def test_filter_on_odd_tables(spark, tmp_path, method):
    schema = "doc_id long, text string, yhat int, query_id string"
    rows = [(None, "a", 1, "x"), (1, None, 1, "x"), (1, "b the b", 1, "x"), (1, "b the b", 1, "x"), *((i, f"word the {i}", 1, "x") for i in range(2, 30)), (30, "", None, None)]
    cfg = Config(epochs_joint=2, epochs_late=1, epochs_head=3)
    for part in (rows[:0], rows[:1], rows):
        df = spark.createDataFrame(part, schema)
        scores = df.filter("doc_id IS NOT NULL").selectExpr("doc_id", "0.6D AS prob").distinct() if method == "prebuilt_cascade" else None
        got = sem_filter(df, counted(tmp_path), "x", 0.9, method, cfg, scores=scores)
        ids = sorted(r["doc_id"] for r in got.predictions.collect())
        assert ids == sorted({r[0] for r in part if r[0] is not None})
        assert got.accepted(df).columns == df.columns


def test_two_phase_with_a_band(bench):
    holds(bench, ms.run_two_phase(bench, "smoothed_band"))


def test_paid_batches_survive_a_failure(spark, tmp_path):
    docs = spark.createDataFrame([(i, f"text {i}") for i in range(20)], "doc_id long, text string").coalesce(1)
    inner, flag = counted(tmp_path), tmp_path.parent / f"fail-{uuid.uuid4().hex}"
    flag.write_text("")

    def ask(texts):
        if os.path.exists(flag) and "text 15" in texts:
            raise TimeoutError
        return inner(texts)

    oracle = CallableOracle(ask, "E", batch=4, retries=0)
    with pytest.raises(Exception, match="TimeoutError"):
        oracle.label(docs)
    paid = calls(tmp_path)
    os.remove(flag)
    assert oracle.label(docs).count() == 20 and 0 < paid < 20 and calls(tmp_path) == 20


def test_external_oracle_retries(spark):
    docs = spark.createDataFrame([(i, "yes" if i % 2 else None) for i in range(10)], "doc_id long, text string")
    state = {"left": 1}

    def ask(texts):
        if state["left"]:
            state["left"] -= 1
            raise TimeoutError
        return [0.9 if t == "yes" else 0.1 for t in texts]

    got = CallableOracle(ask, "E", batch=4).label(docs).collect()
    assert sorted((r["doc_id"], r["y"]) for r in got) == [(i, i % 2) for i in range(10)]


def test_draw_mode_floor_holds_on_average(spark, sf01):
    b = ms.Bench.documents(spark, sf01, ("Q04", "Q08"), Config(label_mode="draw"))
    f, p = ms.run_floor(b).runs, ms.run_prebuilt(b, "range_bound").runs
    assert f["n_oracle"].mean() <= p["n_oracle"].mean() * 1.05


def test_centroids_come_from_the_whole_id_range(spark, monkeypatch):
    monkeypatch.setattr(clustering, "FIT_SAMPLE", 50)
    frame = spark.range(400).selectExpr("id AS doc_id", "array(cast(id AS float)) AS emb")
    centre = clustering.fit(frame, 1)
    assert 150 < float(centre[0, 0]) < 250
    ranked = frame.orderBy(clustering.uniform(clustering.F.col("doc_id"), ":fit"), "doc_id").limit(50).toPandas()
    assert centre[0, 0] == pytest.approx(ranked["doc_id"].mean())
