"""Training of one proxy a query in parallel, and scoring of the pool with all of them."""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import features as feat
from ..config import Config
from . import nets

KINDS = ("hybrid", "joint", "late", "mean", "biencoder", "biencoder_soft")


@dataclass
class Proxy:
    """A trained scorer of one query; ``kind`` says which parts it uses."""

    kind: str
    q: np.ndarray
    parts: dict
    seconds: float = 0.0  # that training took

    def backbones(self, emb: np.ndarray, toks: list) -> tuple[np.ndarray, np.ndarray]:
        return self.parts["joint"].prob(self.q, emb, toks), self.parts["late"].prob(self.q, emb, toks)

    def prob(self, emb: np.ndarray, toks: list) -> np.ndarray:
        if self.kind.startswith("biencoder"):
            return self.parts["bi"].prob(self.q, emb)
        js, li = self.backbones(emb, toks)
        if self.kind == "joint":
            return js
        if self.kind == "late":
            return li
        return (js + li) / 2 if self.kind == "mean" else self.parts["head"].prob(js, li)


def fit_proxy(kind: str, asks: str, t: pd.DataFrame, c: pd.DataFrame | None, cfg: Config, *, backbones: str = "soft", use_dual: bool = True, use_cov: bool = True, old: Proxy | None = None) -> Proxy:
    """Trains on T (``emb, toks, p_star, y``); the head also holds its risk on C if there is one.

    ``backbones`` is soft, hard or contrastive; ``old`` lends its backbones, so that only the head is trained.
    """
    t = t.sort_values("doc_id")
    emb, toks = np.stack(t["emb"].to_numpy()).astype(float), list(t["toks"])
    p, y = t["p_star"].to_numpy(float), t["y"].to_numpy(float)
    q = feat.embed(asks, emb.shape[1]).astype(float)
    if kind.startswith("biencoder"):
        bi = nets.BiEncoder(emb.shape[1], seed=cfg.seed)
        if kind == "biencoder":
            for stage in (1, 2, 3):
                bi.contrast(q, emb, y, cfg.epochs_joint, cfg.lr, stage)
            bi.calibrate(q, emb, y)
        else:
            bi.soft(q, emb, p, 2 * cfg.epochs_joint, cfg.lr)
        return Proxy(kind, q, {"bi": bi})
    if old is None:
        joint = nets.JointScorer(emb.shape[1], cfg.joint_hidden, cfg.seed)
        late = nets.LateScorer.seeded(feat.token_ids(asks), cfg.tok_dim, cfg.late_dim, cfg.seed)
        if backbones == "contrastive":
            nets.fit_contrastive(joint, q, emb, toks, y, cfg.epochs_joint, cfg)
            nets.fit_contrastive(late, q, emb, toks, y, cfg.epochs_late, cfg)
        else:
            target = y if backbones == "hard" else p
            nets.fit_scorer(joint, q, emb, toks, target, cfg.epochs_joint, cfg, cfg.seed)
            nets.fit_scorer(late, q, emb, toks, target, cfg.epochs_late, cfg, cfg.seed, lr=10 * cfg.lr)
        parts = {"joint": joint, "late": late}
    else:
        parts = {"joint": old.parts["joint"], "late": old.parts["late"]}
    out = Proxy(kind, q, parts)
    if kind == "hybrid":
        head = nets.HybridHead(cfg.head_hidden, cfg.seed)
        js, li = out.backbones(emb, toks)
        con = None
        if c is not None and len(c):
            c = c.sort_values("doc_id")
            cj, cl = out.backbones(np.stack(c["emb"].to_numpy()).astype(float), list(c["toks"]))
            con = (cj, cl, c["y"].to_numpy(float))
        parts["dual_trace"] = head.fit((js, li, p, y), con, cfg, use_dual, use_cov, hard=backbones == "hard")
        parts["head"] = head
    return out


def train_all(labelled: DataFrame, kind: str, asks: dict[str, str], cfg: Config, old: dict[str, Proxy] | None = None, **flags) -> dict[str, Proxy]:
    """One proxy a query, fitted in parallel from ``query_id, part (train or cal), doc_id, emb, toks, p_star, y``.

    Labelled sets are small by construction (a share of the corpus, or its cap); weights come back as bytes.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        q, began = pdf["query_id"].iloc[0], time.time()
        t, c = pdf[pdf["part"] == "train"], pdf[pdf["part"] == "cal"]
        model = fit_proxy(kind, asks[q], t, c, cfg, old=(old or {}).get(q), **flags)
        return pd.DataFrame({"query_id": [q], "weights": [pickle.dumps((model.kind, model.q, {k: _state(v) for k, v in model.parts.items()}))], "seconds": [time.time() - began]})

    got = labelled.groupBy("query_id").applyInPandas(run, "query_id string, weights binary, seconds double").toPandas()
    return {q: replace(_load(bytes(w), cfg, asks[q]), seconds=s) for q, w, s in got.itertuples(index=False)}


def _state(part):
    if isinstance(part, nets.BiEncoder):
        return [part.q.params, part.d.params, part.affine]
    if isinstance(part, (nets.JointScorer, nets.HybridHead)):
        return part.net.params
    return part.params if isinstance(part, nets.LateScorer) else part


def _load(blob: bytes, cfg: Config, asks: str) -> Proxy:
    kind, q, state = pickle.loads(blob)
    parts = {}
    for name, s in state.items():
        if name == "bi":
            parts[name] = m = nets.BiEncoder(len(q), seed=cfg.seed)
            m.q.params, m.d.params, m.affine = s
        elif name == "joint":
            parts[name] = m = nets.JointScorer(len(q), cfg.joint_hidden, cfg.seed)
            m.net.params = s
        elif name == "late":
            parts[name] = m = nets.LateScorer.seeded(feat.token_ids(asks), cfg.tok_dim, cfg.late_dim, cfg.seed)
            m.proj, m.free, m.affine = s
        elif name == "head":
            parts[name] = m = nets.HybridHead(cfg.head_hidden, cfg.seed)
            m.net.params = s
        else:
            parts[name] = s
    return Proxy(kind, q, parts)


def score(features: DataFrame, models: dict[str, Proxy]) -> DataFrame:
    """``query_id, doc_id, prob`` of every document under every query's proxy: one narrow pass; the
    models, a few hundred kilobytes a query, travel with the task."""
    local = dict(models)

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for p in parts:
            if not len(p):
                continue
            emb, toks = np.stack(p["emb"].to_numpy()).astype(float), list(p["toks"])
            for q, m in local.items():
                yield pd.DataFrame({"query_id": q, "doc_id": p["doc_id"], "prob": np.clip(m.prob(emb, toks), 1e-9, 1 - 1e-9)})

    return features.select("doc_id", "emb", "toks").mapInPandas(run, "query_id string, doc_id long, prob double").withColumn("conf", F.round(F.abs(F.col("prob") - 0.5) * 2, 9)).withColumn("yhat", (F.col("prob") >= 0.5).cast("int"))
