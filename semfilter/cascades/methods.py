"""The methods end to end, for many queries at once: every frame is keyed by query."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .. import bayes, clustering, metrics
from .. import features as feat
from ..calibrate import threshold as th
from ..config import Config
from ..oracle import ORACLE_MS, PREBUILT_MS, Ledger, PlantedOracle, uniform
from ..proxy import train as px
from ..sampling import split_sample, stratified_sample
from ..sources import catalogue as cat
from ..sources.tables import corpus, save, table

KEYS = ["query_id", "doc_id"]
PROXY_S = {"hybrid": 15.2, "biencoder": 79.2, "prebuilt": 0.0, "none": 0.0}


@dataclass
class Bench:
    """A corpus, its predicates, an oracle that labels what the ledger asks for, and the vectors.

    ``answers`` holds all answers where they are known, for measures and for the floor; a live filter has none, and
    nothing but the ledger's requests reaches its ``oracle``. ``prior`` has the scores of a pre-trained scorer, ``query_id, doc_id, prob, tokens``.
    """

    spark: SparkSession
    queries: tuple[str, ...]
    asks: dict[str, str]
    answers: DataFrame | None
    features: DataFrame
    n: int
    cfg: Config
    name: str = "documents"
    oracle: object | None = None
    prior: DataFrame | None = None

    @classmethod
    def documents(cls, spark: SparkSession, sf_dir: str, queries: tuple[str, ...], cfg: Config | None = None, name: str = "documents") -> Bench:
        """A text corpus with planted predicates; answers and vectors are written once a session."""
        cfg = cfg or Config()
        key = (spark.sparkContext.applicationId, sf_dir, tuple(queries), cfg.label_mode, name, cfg.emb_dim)
        if key not in _KEPT:
            docs = corpus(spark, sf_dir, name)
            answers = save(PlantedOracle(spark, sf_dir, queries, cfg.label_mode, None if name == "documents" else docs).answers())
            fkey = key[:2] + key[4:]
            if fkey not in _VECTORS:
                _VECTORS[fkey] = save(feat.build(docs, cfg.emb_dim))
            _KEPT[key] = (answers, _VECTORS[fkey], _VECTORS[fkey].count())
        answers, vectors, n = _KEPT[key]
        c = cat.catalogue()
        return cls(spark, tuple(queries), {q: c[q].asks for q in queries}, answers, vectors, n, cfg.scaled(n), name)

    @classmethod
    def vectors(cls, spark: SparkSession, sf_dir: str, cfg: Config | None = None) -> Bench:
        """The corpus without text: a half-space that a scorer can learn, and a label that nothing predicts."""
        cfg = cfg or Config()
        e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), F.col("embedding").alias("emb"), F.array().cast("array<int>").alias("toks"), "label")
        first = e.filter("doc_id = 0").select(F.col("emb").alias("e0"))
        dot = F.expr("aggregate(zip_with(emb, e0, (x, y) -> cast(x as double) * y), 0D, (s, v) -> s + v)")
        half = 1 / (1 + F.exp(-60 * dot))
        odd = F.when(F.col("label") == 3, 0.95).otherwise(0.05)
        wide = e.crossJoin(F.broadcast(first)).select("doc_id", F.explode(F.array(F.struct(F.lit("half_space").alias("q"), half.alias("p")), F.struct(F.lit("chance").alias("q"), odd.alias("p")))).alias("r"))
        y = (F.col("r.p") >= 0.5).cast("int")
        answers = save(wide.select(F.col("r.q").alias("query_id"), "doc_id", F.col("r.p").alias("p_star"), y.alias("y"), F.lit(100).cast("long").alias("tokens"), F.col("r.p").alias("prob")))
        n = e.count()
        asks = {"half_space": "close to the first vector", "chance": "of the fourth class"}
        return cls(spark, tuple(asks), asks, answers, save(e.drop("label")), n, cfg.scaled(n), "embeddings")

    def pairs(self) -> DataFrame:
        """Every (query, document), from the ids alone."""
        return self.features.select(F.explode(F.array(*map(F.lit, self.queries))).alias("query_id"), "doc_id")

    def ledger(self) -> Ledger:
        return Ledger(self.answers if self.oracle is None else self.oracle, self.spark)

    def only(self, queries: tuple[str, ...]) -> Bench:
        """The same for some of the queries."""
        few = F.col("query_id").isin(list(queries))
        return replace(self, queries=queries, answers=None if self.answers is None else self.answers.filter(few), prior=None if self.prior is None else self.prior.filter(few))

    def known(self) -> DataFrame:
        if self.answers is None:
            raise ValueError("this method needs every answer of the oracle beforehand")
        return self.answers


_KEPT: dict = {}
_VECTORS: dict = {}


@dataclass
class Result:
    """Predictions with their origin, the ledger, and one row a query of what the run cost and reached."""

    method: str
    predictions: DataFrame
    ledger: DataFrame
    runs: pd.DataFrame
    trace: list = field(default_factory=list)

    def runs_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.runs)


def _finish(b: Bench, method: str, pred: DataFrame, ledger: DataFrame, proxy: dict[str, float] | float = 0.0, extra: dict | None = None, wall: float = 0.0, trace: list | None = None, calls: dict | None = None) -> Result:
    """Accounts for a run: end-to-end cost is proxy seconds plus calls times their latency."""
    pred = save(pred.select(*KEYS, "yhat", "origin"))
    acc = None if b.answers is None else metrics.accuracy(pred, b.answers).toPandas().set_index("query_id")
    paid = metrics.oracle_calls(ledger).toPandas().set_index("query_id").reindex(list(b.queries)).fillna(0)
    rows = []
    for q in b.queries:
        p = proxy[q] if isinstance(proxy, dict) else proxy
        oracle_s = float(paid.loc[q, "oracle_tokens"]) * ORACLE_MS / 1000
        a, f1 = (float("nan"), float("nan")) if acc is None else (float(acc.loc[q, "accuracy"]), float(acc.loc[q, "f1"]))
        own = (extra or {}).get(q, {})
        rows.append({
            "method": method, "corpus": b.name, "query_id": q, "alpha": b.cfg.alpha, "accuracy": a, "f1": f1,
            **{f"n_{k}": int(paid.loc[q, f"n_{k}"]) for k in metrics.PURPOSES}, "n_oracle": int(calls[q] if calls else paid.loc[q, "n_oracle"]),
            "proxy_s": p, "oracle_s": oracle_s, "e2e_s": p + oracle_s, "sla_hit": int(a >= b.cfg.alpha - 1e-12), "sla_gap": max(0.0, b.cfg.alpha - a),
            "phase2": bool(own.get("phase2", False)), "tau": float(own.get("tau", float("nan"))), "train_s": float(own.get("train_s", 0.0)), "score_s": float(own.get("score_s", 0.0)), "wall_s": wall,
        })
    return Result(method, pred, ledger, pd.DataFrame(rows), trace or [])


def run_exhaustive(b: Bench) -> Result:
    """The oracle on every document."""
    led = b.ledger()
    got = led.request(b.pairs(), "cascade")
    return _finish(b, "exhaustive", got.select(*KEYS, F.col("y").alias("yhat"), F.lit("oracle").alias("origin")), led.rows)


def run_floor(b: Bench) -> Result:
    """The floor as a pseudo-method: the surest answers are given, the rest is called; not deployable."""
    fl = {r["query_id"]: int(r["floor_calls"]) for r in bayes.bayes_floor(b.known(), [b.cfg.alpha]).collect()}
    by = W.partitionBy("query_id").orderBy(F.desc(F.round(bayes.eta(F.col("p_star")), 9)), "doc_id")
    floors = b.spark.createDataFrame([(q, v) for q, v in fl.items()], "query_id string, k long")
    marked = b.answers.join(F.broadcast(floors), "query_id").withColumn("call", F.row_number().over(by) <= F.col("k"))
    led = b.ledger()
    led.request(marked.filter("call"), "cascade")
    pred = marked.select(*KEYS, F.when(F.col("call"), F.col("y")).otherwise((F.col("p_star") >= 0.5).cast("int")).alias("yhat"), F.when(F.col("call"), "oracle").otherwise("auto").alias("origin"))
    return _finish(b, "bayes_floor", pred, led.rows)


def calibrate(b: Bench, scores: DataFrame, cal: DataFrame, ledger: DataFrame, method: str = "blend") -> dict[str, th.Choice]:
    """Thresholds of all queries: calibration labels are collected (few by construction), the pool is counted once."""
    labelled = scores.join(cal.select(*KEYS, "y"), KEYS).withColumn("wrong", (F.col("yhat") != F.col("y")).cast("int")).toPandas()
    groups = {q: g for q, g in labelled.groupby("query_id")}
    empty = labelled.iloc[:0]
    pool = scores if b.cfg.pool_scope == "all" else scores.join(ledger.select(*KEYS), KEYS, "left_anti")
    if method == "smoothed_band":
        g = b.cfg.hist_ranges
        cell = F.least(F.floor(F.col("prob") * g), F.lit(g - 1)).cast("int")
        seen = pool.groupBy("query_id", cell.alias("at")).count().toPandas()
        out = {}
        for q in b.queries:
            counts = np.zeros(g, int)
            for _, at, n in seen[seen["query_id"] == q].itertuples(index=False):
                counts[at] = n
            own = groups.get(q, empty)
            out[q] = th.select_band(own["prob"].to_numpy(), own["y"].to_numpy(), counts, b.n, b.cfg)
        return out
    cuts = {q: th.cut_points(np.round(groups.get(q, empty)["conf"].to_numpy(float), 9), b.cfg) for q in b.queries}
    counts = th.pool_counts(pool, cuts)
    return {q: th.select_tau(groups.get(q, empty)["conf"].to_numpy(float), groups.get(q, empty)["wrong"].to_numpy(int), cuts[q], counts[q], b.n, b.cfg, method) for q in b.queries}


def deploy(b: Bench, scores: DataFrame, choices: dict, led: Ledger) -> DataFrame:
    """Documents at or above their query's threshold keep the proxy's guess, the others go to the oracle."""
    if choices and isinstance(next(iter(choices.values())), tuple):
        cut = b.spark.createDataFrame([(q, float(c[0]), float(c[1])) for q, c in choices.items()], "query_id string, lo double, hi double")
        accept = (F.col("prob") < F.col("lo")) | (F.col("prob") >= F.col("hi"))
    else:
        cut = b.spark.createDataFrame([(q, float(c.tau)) for q, c in choices.items()], "query_id string, tau double")
        accept = F.col("conf") >= F.col("tau")
    marked = scores.join(F.broadcast(cut), "query_id").withColumn("accept", accept)
    led.request(marked.filter(~F.col("accept")), "cascade")
    known = led.rows.select(*KEYS, "y")
    return marked.join(known, KEYS, "left").select(*KEYS, F.coalesce("y", "yhat").alias("yhat"), F.when(F.col("y").isNotNull(), "oracle").otherwise("auto").alias("origin"))


def prebuilt_scores(b: Bench) -> DataFrame:
    if b.prior is None and b.answers is None:
        raise ValueError("a prebuilt scorer's scores are needed")
    return (b.answers if b.prior is None else b.prior).select(*KEYS, "prob", F.round(F.abs(F.col("prob") - 0.5) * 2, 9).alias("conf"), (F.col("prob") >= 0.5).cast("int").alias("yhat"))


def run_prebuilt(b: Bench, method: str = "uniform_margin") -> Result:
    """A pre-trained scorer on every document, a small calibration set, a margin, and the oracle below it."""
    began, led = time.time(), b.ledger()
    cal = led.request(split_sample(b.pairs(), b.cfg.train_frac, b.cfg.cal_frac).filter("part = 'cal'"), "cal")
    scores = prebuilt_scores(b)
    choices = calibrate(b, scores, cal, led.rows, method)
    pred = deploy(b, scores, choices, led)
    tokens = {r[0]: r[1] for r in (b.answers if b.prior is None else b.prior).groupBy("query_id").sum("tokens").collect()}
    extra = {q: {"tau": _tau(c)} for q, c in choices.items()}
    return _finish(b, "prebuilt_cascade", pred, led.rows, {q: tokens.get(q, 0) * PREBUILT_MS / 1000 for q in b.queries}, extra, time.time() - began)


def run_trained(b: Bench, kind: str = "hybrid", cal_method: str = "blend", name: str | None = None, flags: dict | None = None, old: dict | None = None, start: Start | None = None) -> Result:
    """A cascade over a proxy trained for each query on uniform 7 % and calibrated on uniform 5 %, or on the labels of ``start``."""
    began, led = time.time(), b.ledger()
    if start is None:
        parts = split_sample(b.pairs(), b.cfg.train_frac, b.cfg.cal_frac)
        t = led.request(_capped(parts.filter("part = 'train'"), b.cfg.train_cap), "train")
        c = led.request(_capped(parts.filter("part = 'cal'"), b.cfg.cal_cap), "cal")
    else:
        led.rows, t, c = start.rows, start.train, start.cal
    models = px.train_all(_with_vectors(b, t, c), kind, b.asks, b.cfg, old, **(flags or {}))
    scores, score_s = _scored(b, models)
    choices = calibrate(b, scores, _held_out(b, c), led.rows, cal_method)
    pred = deploy(b, scores, choices, led)
    extra = {q: {"tau": _tau(x), "phase2": True, "train_s": models[q].seconds, "score_s": score_s} for q, x in choices.items()}
    out = _finish(b, name or ("biencoder_cascade" if kind.startswith("bi") else "hybrid_cascade"), pred, led.rows, PROXY_S["biencoder" if kind.startswith("bi") else "hybrid"], extra, time.time() - began)
    out.trace = [models, choices]
    return out


def _tau(choice) -> float:
    return choice[0] if isinstance(choice, tuple) else choice.tau


def _scored(b: Bench, models: dict) -> tuple[DataFrame, float]:
    """Scores of all documents, written, and the seconds that took for each query."""
    began = time.time()
    scores = save(px.score(b.features, models))
    return scores, (time.time() - began) / max(1, len(models))


def _held_out(b: Bench, c: DataFrame) -> DataFrame:
    """With ``split_cal``, only the half of C that the constraint did not see calibrates."""
    return c.filter(uniform(F.col("doc_id"), ":half") >= 0.5) if b.cfg.split_cal else c


def _capped(pairs: DataFrame, cap: int | None) -> DataFrame:
    if cap is None:
        return pairs
    by = W.partitionBy("query_id").orderBy(uniform(F.col("doc_id"), ":cap"), "doc_id")
    return pairs.withColumn("_r", F.row_number().over(by)).filter(F.col("_r") <= cap).drop("_r")


def _with_vectors(b: Bench, t: DataFrame, c: DataFrame | None) -> DataFrame:
    rows = t.withColumn("part", F.lit("train"))
    if c is not None:
        seen = c.filter(uniform(F.col("doc_id"), ":half") < 0.5) if b.cfg.split_cal else c
        rows = rows.unionByName(seen.withColumn("part", F.lit("cal")))
    return rows.join(b.features, "doc_id").select("query_id", "part", "doc_id", "emb", "toks", "p_star", "y")


@dataclass
class Vote:
    """Where voting ended: clusters with their majority, members left open, and the ledger."""

    clusters: DataFrame
    majority: dict[tuple[str, str], int]
    open_: set[tuple[str, str]]
    rounds: list[dict]


def vote(b: Bench, led: Ledger, budget: float) -> Vote:
    """Cluster, sample, label, vote; split what disagrees and vote again, until all agree or the budget is used.

    Only a few rows a cluster come to the driver. The budget is looked at after every cluster in a fixed
    order, or after each round. A cluster too small to split, or that does not split, is labelled whole.
    """
    size, limit = b.cfg.vote_size(b.n), budget * b.n
    centres = clustering.fit(b.features, b.cfg.k_initial, b.cfg.seed, b.n)
    base = clustering.assign(b.features, centres)
    now = save(base.select(F.explode(F.array(*map(F.lit, b.queries))).alias("query_id"), "doc_id", "cluster_id"))
    everything, majority, trace, spent = now, {}, [], dict.fromkeys(b.queries, 0)
    active = {(r[0], r[1]): int(r[2]) for r in now.groupBy("query_id", "cluster_id").count().collect()}
    left: set = set()
    for round_ in range(b.cfg.max_rounds):
        if not active:
            break
        allowed, stopped = [], set()
        plan = dict(spent)
        for key in sorted(active):
            over = plan[key[0]] >= limit if b.cfg.budget_check == "cluster" else spent[key[0]] >= limit
            if over:
                stopped.add(key)
            else:
                allowed.append(key)
                plan[key[0]] += min(size, active[key])
        left |= stopped
        if not allowed:
            break
        chosen = b.spark.createDataFrame([(q, c, active[(q, c)] <= size) for q, c in allowed], "query_id string, cluster_id string, whole boolean")
        members = now.join(F.broadcast(chosen), ["query_id", "cluster_id"])
        fresh = members if b.cfg.pool_parent_labels else members.join(led.rows.select(*KEYS), KEYS, "left_anti")
        by = W.partitionBy("query_id", "cluster_id").orderBy(uniform(F.col("doc_id"), f":vote{round_}"), "doc_id")
        wanted = fresh.withColumn("_r", F.row_number().over(by)).filter((F.col("_r") <= size) | F.col("whole"))
        led.request(wanted, "vote", round_)
        ballots = led.rows if b.cfg.pool_parent_labels else led.rows.filter((F.col("round") == round_) & (F.col("purpose") == "vote"))
        # of a cluster labelled whole, labels of earlier rounds count as well
        tally = members.join(led.rows.select(*KEYS, "y", "round", "purpose"), KEYS).filter(F.col("whole") | (F.col("round") == round_)) if not b.cfg.pool_parent_labels else members.join(ballots.select(*KEYS, "y"), KEYS)
        votes = {(r[0], r[1]): (int(r[2]), int(r[3])) for r in tally.groupBy("query_id", "cluster_id").agg(F.count("*"), F.sum("y")).collect()}
        spent = {**dict.fromkeys(b.queries, 0), **{r[0]: int(r[1]) for r in led.rows.groupBy("query_id").count().collect()}}
        failed = []
        for key in allowed:
            n, yes = votes.get(key, (0, 0))
            share = max(yes, n - yes) / n if n else 0.0
            done = active[key] <= size or share >= b.cfg.agreement() - 1e-12
            trace.append({"query_id": key[0], "cluster_id": key[1], "round": round_, "size": active[key], "n_votes": n, "agreement": share, "passed": int(done)})
            if done:
                majority[key] = int(2 * yes >= n)
            else:
                failed.append(key)
        if not failed:
            active = {}
            break
        bad = b.spark.createDataFrame(failed, "query_id string, cluster_id string")
        parents = now.join(F.broadcast(bad), ["query_id", "cluster_id"])
        children = save(clustering.bisect(parents, b.features, b.cfg.seed + round_))
        sizes = {(r[0], r[1]): int(r[2]) for r in children.groupBy("query_id", "cluster_id").count().collect()}
        lone = {k for k in sizes if (k[0], k[1][:-1] + ("1" if k[1][-1] == "0" else "0")) not in sizes}
        everything = save(everything.join(F.broadcast(bad), ["query_id", "cluster_id"], "left_anti").unionByName(children))
        if lone:  # k-means found one side only: label every member
            rest = children.join(F.broadcast(b.spark.createDataFrame(sorted(lone), "query_id string, cluster_id string")), ["query_id", "cluster_id"])
            led.request(rest, "vote", round_)
            majority.update(dict.fromkeys(lone, 0))
        now, active = children, {k: v for k, v in sizes.items() if k not in lone}
    left |= set(active) if active else set()
    return Vote(everything, majority, left, trace)


def propagate(b: Bench, v: Vote, led: Ledger) -> DataFrame:
    """Majorities to whole clusters; documents with a label of their own keep it."""
    maj = b.spark.createDataFrame([(q, c, m) for (q, c), m in v.majority.items()], "query_id string, cluster_id string, m int")
    j = v.clusters.join(F.broadcast(maj), ["query_id", "cluster_id"], "left").join(led.rows.select(*KEYS, "y"), KEYS, "left")
    return j.select(*KEYS, F.coalesce("y", "m").alias("yhat"), F.when(F.col("y").isNotNull(), "oracle").otherwise("propagated").alias("origin"))


def run_cluster_vote(b: Bench) -> Result:
    """Voting alone: no budget, and what is left open goes to the oracle."""
    began, led = time.time(), b.ledger()
    v = vote(b, led, 1.0)
    if v.open_:
        rest = v.clusters.join(F.broadcast(b.spark.createDataFrame(sorted(v.open_), "query_id string, cluster_id string")), ["query_id", "cluster_id"])
        led.request(rest, "cascade")
    return _finish(b, "cluster_vote", propagate(b, v, led), led.rows, wall=time.time() - began, trace=v.rounds)


@dataclass
class Start:
    """What the second phase starts from: all labels bought so far, T and C among them, and the proxy trained on T alone."""

    rows: DataFrame
    train: DataFrame
    cal: DataFrame
    first: dict


def _second_labels(b: Bench, led: Ledger, opened: tuple[str, ...], cal_source: str) -> Start:
    """T is what the first phase bought for the queries left open; C is bought here."""
    sub, few = b.only(opened), F.col("query_id").isin(list(opened))
    t = led.reuse(["vote"], "train").filter(few)
    first = px.train_all(_with_vectors(sub, t, None), "hybrid", b.asks, b.cfg)
    if cal_source == "phase1":
        c = t
    else:
        pool = px.score(b.features, first).join(led.rows.select(*KEYS), KEYS, "left_anti")
        c = led.request(_capped(stratified_sample(pool, b.cfg.cal_frac, b.cfg.strata), b.cfg.cal_cap), "cal")
    return Start(led.rows.filter(few), t, c, first)


def fired(b: Bench) -> tuple[Bench, Start | None]:
    """The queries that voting within 7 % of labels leaves open, and what cascades over them start from; none if all are done."""
    led = b.ledger()
    opened = tuple(sorted({q for q, _ in vote(b, led, b.cfg.phase1_frac).open_}))
    if not opened:
        return b.only(opened), None
    s = _second_labels(b, led, opened, "stratified")
    rows = save(s.rows)
    return b.only(opened), replace(s, rows=rows, train=rows.filter("purpose = 'vote'").withColumn("purpose", F.lit("train")))


def run_two_phase(b: Bench, cal_method: str = "blend", cal_source: str = "stratified") -> Result:
    """Voting within 7 % of labels; queries that it does not finish train the hybrid proxy on those labels.

    Propagated labels are dropped, bought ones are kept as T; C is bought fresh, stratified on a provisional
    head's score, since phase 1's labels are not a uniform sample. ``cal_source='phase1'`` reuses them all
    the same, as a negative control.
    """
    began, led = time.time(), b.ledger()
    v = vote(b, led, b.cfg.phase1_frac)
    opened = {q for q, _ in v.open_}
    voted = propagate(b, v, led).filter(~F.col("query_id").isin(sorted(opened)))
    extra = {q: {"phase2": q in opened} for q in b.queries}
    pred, trace = voted, [v.rounds]
    if opened:
        sub = b.only(tuple(sorted(opened)))
        s = _second_labels(b, led, sub.queries, cal_source)
        t, c, first = s.train, s.cal, s.first
        models = px.train_all(_with_vectors(sub, t, c), "hybrid", b.asks, b.cfg, first)
        scores, score_s = _scored(sub, models)
        choices = calibrate(sub, scores, _held_out(b, c), led.rows, cal_method)
        pred = pred.unionByName(deploy(sub, scores, choices, led))
        for q, x in choices.items():
            extra[q] |= {"tau": _tau(x), "train_s": first[q].seconds + models[q].seconds, "score_s": score_s}
        trace += [models, choices]
    proxy = {q: PROXY_S["hybrid"] if q in opened else 0.0 for q in b.queries}
    return _finish(b, "two_phase", pred, led.rows, proxy, extra, time.time() - began, trace)


def run_router(b: Bench, by: str = "calls", pilot_frac: float = 0.02, reuse: bool = False, crossover: float = 0.02) -> Result:
    """Picks a method for each query from a pilot sample: by dry-run cost (labels thrown away), or by Bayes error."""
    began, led = time.time(), b.ledger()
    pilot = led.request(b.pairs().filter(uniform(F.col("doc_id"), ":", F.col("query_id"), ":pilot") < pilot_frac), "pilot")
    if by == "ber":
        low = {r["query_id"]: float(r["ber"]) < crossover for r in bayes.pilot_ber(pilot).collect()}
    else:
        base = clustering.assign(b.features, clustering.fit(b.features, b.cfg.k_initial, b.cfg.seed, b.n))
        shares = pilot.join(base, "doc_id").groupBy("query_id", "cluster_id").agg(F.avg("y").alias("a"))
        agree = shares.groupBy("query_id").agg(F.min(F.greatest("a", 1 - F.col("a"))).alias("m"))
        low = {r["query_id"]: float(r["m"]) >= b.cfg.agreement() for r in agree.collect()}
    easy = tuple(q for q in b.queries if low.get(q, False))
    hard = tuple(q for q in b.queries if q not in easy)
    done: list[Result] = []
    for own, run in ((easy, run_cluster_vote), (hard, run_trained)):
        if own:
            done.append(run(b.only(own)))
    pred, ledger = done[0].predictions, done[0].ledger
    for r in done[1:]:
        pred, ledger = pred.unionByName(r.predictions), ledger.unionByName(r.ledger)
    paid = pilot.join(ledger.select(*KEYS), KEYS, "left_anti") if reuse else pilot
    proxy = {q: PROXY_S["hybrid"] if q in hard else 0.0 for q in b.queries}
    return _finish(b, "ber_router" if by == "ber" else "router", pred, ledger.unionByName(paid), proxy, {q: {"phase2": q in hard} for q in b.queries}, time.time() - began)


def nothing(b: Bench, method: str) -> Result:
    """What any method gives for no documents: no decision, no call."""
    none = b.spark.createDataFrame([], "query_id string, doc_id long, yhat int, origin string")
    return _finish(replace(b, answers=None), method, none, b.ledger().rows)


METHODS: dict[str, Callable[[Bench], Result]] = {
    "exhaustive": run_exhaustive,
    "cluster_vote": run_cluster_vote,
    "prebuilt_cascade": run_prebuilt,
    "biencoder_cascade": lambda b: run_trained(b, "biencoder", "smoothed_histogram"),
    "hybrid_cascade": run_trained,
    "two_phase": run_two_phase,
    "bayes_floor": run_floor,
}
