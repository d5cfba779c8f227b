"""Small scorers in numpy: joint, late-interaction, head, two towers; soft, constrained and contrastive training."""

from __future__ import annotations

import numpy as np

from ..config import Config
from ..features import token_vectors

#: Document tokens whose matches are held at a time.
TOKENS = 1 << 18
#: Documents that go through a joint network at a time.
ROWS = 4096


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def confidence(p: np.ndarray) -> np.ndarray:
    return 2 * np.abs(p - 0.5)


def bce(p: np.ndarray, target: np.ndarray) -> float:
    """Cross-entropy against a probability or a hard label."""
    p = np.clip(p, 1e-7, 1 - 1e-7)
    return float(np.mean(-target * np.log(p) - (1 - target) * np.log(1 - p)))


class Adam:
    def __init__(self, params: list[np.ndarray], lr: float):
        self.params, self.lr, self.t = params, lr, 0
        self.m, self.v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]

    def step(self, grads: list[np.ndarray]) -> None:
        self.t += 1
        for p, g, m, v in zip(self.params, grads, self.m, self.v, strict=True):
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            p -= self.lr * (m / (1 - 0.9**self.t)) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8)


class MLP:
    """Dense layers with ReLU between them."""

    def __init__(self, sizes: list[int], seed: int):
        rng = np.random.default_rng(seed)
        self.params = [x for a, b in zip(sizes, sizes[1:], strict=False) for x in (rng.normal(size=(a, b)) * np.sqrt(2 / a), np.zeros(b))]

    def forward(self, x: np.ndarray, keep: list | None = None) -> np.ndarray:
        last = len(self.params) // 2 - 1
        for k in range(last + 1):
            if keep is not None:
                keep.append(x)
            x = x @ self.params[2 * k] + self.params[2 * k + 1]
            if k < last:
                x = np.maximum(x, 0)
        return x

    def backward(self, keep: list, grad: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
        grads: list[np.ndarray] = []
        for k in range(len(self.params) // 2 - 1, -1, -1):
            x = keep[k]
            grads = [x.T @ grad, grad.sum(axis=0), *grads]
            grad = grad @ self.params[2 * k].T
            if k:
                grad = grad * (x > 0)
        return grads, grad

    def count(self) -> int:
        return sum(p.size for p in self.params)


def joint_input(q: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Query and document vectors side by side, their product and their gap."""
    q = np.broadcast_to(q, d.shape)
    return np.concatenate([q, d, q * d, np.abs(q - d)], axis=1)


class JointScorer:
    """One network over query and document together."""

    def __init__(self, dim: int, hidden: int, seed: int = 42):
        self.net = MLP([4 * dim, hidden, 1], seed)

    def prob(self, q: np.ndarray, emb: np.ndarray, toks=None) -> np.ndarray:
        return np.concatenate([sigmoid(self.net.forward(joint_input(q, emb[k : k + ROWS]))[:, 0]) for k in range(0, max(1, len(emb)), ROWS)])

    def grad(self, q, emb, toks, target):
        keep: list = []
        p = sigmoid(self.net.forward(joint_input(q, emb), keep)[:, 0])
        return self.net.backward(keep, ((p - target) / len(p))[:, None])[0]

    @property
    def params(self):
        return self.net.params


def maxsim(q: np.ndarray, d: np.ndarray) -> float:
    """Sum over query tokens of the best match among the document's tokens."""
    return float((q @ d.T).max(axis=1).sum()) if len(d) and len(q) else 0.0


class LateScorer:
    """A shared projection of token vectors, the best document token for each query token, and a slope and offset.

    Query tokens are those of the predicate and a few free ones that training fills.
    """

    def __init__(self, q_toks: np.ndarray, table: np.ndarray, out: int, seed: int = 42, free: int = 4):
        rng = np.random.default_rng(seed)
        self.table, self.q_toks = table, np.asarray(q_toks, int)
        self.proj = rng.normal(size=(table.shape[1], out)) / np.sqrt(out)
        self.free = rng.normal(size=(free, table.shape[1])) * 0.3
        self.affine = np.array([1.0, 0.0])
        self.made: tuple | None = None

    @classmethod
    def seeded(cls, q_toks: np.ndarray, dim: int, out: int, seed: int) -> LateScorer:
        """With the seeded table, which is left out of what travels: every process makes it itself."""
        m = cls(q_toks, token_vectors(dim, seed), out, seed)
        m.made = (dim, seed)
        return m

    def __getstate__(self) -> dict:
        return self.__dict__ if self.made is None else self.__dict__ | {"table": None}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        if self.made is not None:
            self.table = token_vectors(*self.made)

    @property
    def params(self):
        return [self.proj, self.free, self.affine]

    def _queries(self) -> np.ndarray:
        return np.concatenate([self.table[self.q_toks], self.free]) if len(self.q_toks) else self.free

    def _score(self, toks: list, keep: list | None = None) -> np.ndarray:
        q = self._queries() @ self.proj
        size = np.array([len(t) for t in toks])
        flat = np.concatenate([np.asarray(t, int) for t in toks]) if size.sum() else np.empty(0, int)
        out = np.zeros(len(toks))
        full = np.flatnonzero(size)
        if len(flat):
            sims = (self.table @ self.proj) @ q.T
            cuts = (np.cumsum(size) - size)[full]
            best, ends, at = np.empty((len(full), len(q))), np.append(cuts[1:], len(flat)), 0
            while at < len(full):
                to = max(at + 1, int(np.searchsorted(ends, cuts[at] + TOKENS, "right")))
                best[at:to] = np.maximum.reduceat(sims[flat[cuts[at] : ends[to - 1]]], cuts[at:to] - cuts[at], axis=0)
                at = to
            out[full] = best.sum(axis=1)
            if keep is not None:
                doc = np.repeat(np.arange(len(full)), size[full])
                win = np.empty(best.shape, int)
                for k in range(best.shape[1]):
                    rows = np.flatnonzero(sims[flat, k] == best[doc, k])
                    _, first = np.unique(doc[rows], return_index=True)
                    win[:, k] = flat[rows[first]]
                keep += [full, win]
        return out

    def prob(self, q, emb, toks) -> np.ndarray:
        return sigmoid(self.affine[0] * self._score(toks) + self.affine[1])

    def grad(self, q, emb, toks, target):
        keep: list = []
        s = self._score(toks, keep)
        p = sigmoid(self.affine[0] * s + self.affine[1])
        g = (p - target) / len(p)
        d_aff = np.array([float((g * s).sum()), float(g.sum())])
        d_proj, d_free = np.zeros_like(self.proj), np.zeros_like(self.free)
        if keep:
            full, win = keep
            queries, n = self._queries(), len(self.q_toks)
            gs = (g * self.affine[0])[full]
            for k in range(win.shape[1]):
                pull = (gs[:, None] * self.table[win[:, k]]).sum(axis=0)
                d_proj += np.outer(pull, queries[k] @ self.proj) + np.outer(queries[k], pull @ self.proj)
                if k >= n:
                    d_free[k - n] += (pull @ self.proj) @ self.proj.T
        return [d_proj, d_free, d_aff]


def head_features(js: np.ndarray, li: np.ndarray) -> np.ndarray:
    """Both scores, their product, their gap and both squares."""
    return np.column_stack([js, li, js * li, np.abs(js - li), js * js, li * li])


def soft_risk(p: np.ndarray, y: np.ndarray, stabiliser: float = 1e-3) -> float:
    """Expected error of accepted answers, each weighed by its confidence."""
    c = confidence(p)
    wrong = np.where(y == 1, 1 - p, p)
    return soft_risk_of(float((c * wrong).sum()), float(c.sum()), stabiliser)


def soft_risk_of(wrong: float, conf: float, stabiliser: float = 1e-3) -> float:
    """The same from its two sums."""
    return wrong / (conf + stabiliser)


def sla_penalty(risk: float, alpha: float, dual: float) -> float:
    return dual * max(0.0, risk - (1 - alpha))


def dual_step(dual: float, risk: float, eps: float, lr: float = 0.5, top: float = 10.0) -> float:
    """Grows with the violation, shrinks when the constraint is met, stays within 0 and ``top``."""
    return float(min(top, max(0.0, dual + lr * (risk - eps))))


def coverage_loss(p: np.ndarray) -> float:
    return float(1 - confidence(p).mean())


def total_loss(soft: float, coverage: float, penalty: float, weight: float = 0.35) -> float:
    return soft + weight * coverage + penalty


class HybridHead:
    """Six features of two scores, two hidden layers, one probability."""

    def __init__(self, hidden: tuple[int, int] = (32, 32), seed: int = 42):
        self.net = MLP([6, *hidden, 1], seed)

    def prob(self, js: np.ndarray, li: np.ndarray) -> np.ndarray:
        return sigmoid(self.net.forward(head_features(js, li))[:, 0])

    def fit(self, t: tuple, c: tuple | None, cfg: Config, use_dual: bool = True, use_cov: bool = True, hard: bool = False) -> list[float]:
        """Soft loss and coverage on T, the constrained risk on C; returns the dual after every epoch.

        ``t`` is (js, li, p_star, y), ``c`` is (js, li, y) or None for a provisional head.
        """
        xt, target = head_features(t[0], t[1]), (t[3] if hard else t[2])
        xc = head_features(c[0], c[1]) if c is not None and use_dual and len(c[0]) else None
        opt, dual, trace = Adam(self.net.params, cfg.lr * 3), cfg.dual_init, []
        for _ in range(cfg.epochs_head):
            keep: list = []
            p = sigmoid(self.net.forward(xt, keep)[:, 0])
            g = (p - target) / len(p)
            if use_cov:
                g = g - cfg.coverage_weight * 2 * np.sign(p - 0.5) * p * (1 - p) / len(p)
            grads, _ = self.net.backward(keep, g[:, None])
            if xc is not None:
                keep = []
                pc = sigmoid(self.net.forward(xc, keep)[:, 0])
                y = c[2]
                conf, wrong, side = confidence(pc), np.where(y == 1, 1 - pc, pc), np.sign(pc - 0.5)
                den = conf.sum() + 1e-3
                risk = float((conf * wrong).sum() / den)
                if risk > 1 - cfg.alpha:
                    gp = (2 * side * wrong + conf * np.where(y == 1, -1.0, 1.0)) / den - risk * 2 * side / den
                    more, _ = self.net.backward(keep, (dual * gp * pc * (1 - pc))[:, None])
                    grads = [a + b for a, b in zip(grads, more, strict=True)]
                dual = dual_step(dual, risk, 1 - cfg.alpha, cfg.dual_lr, cfg.dual_max)
            opt.step(grads)
            trace.append(dual)
        return trace


def pair_hinge(pos: np.ndarray, neg: np.ndarray, margin: float) -> tuple[float, np.ndarray, np.ndarray]:
    """Mean hinge ``margin - pos + neg`` over all pairs, and for each positive and each negative the share of its pairs that are active.

    Sorted once and looked up, so room grows with the numbers and not with their pairs.
    """
    low, high = np.sort(neg), np.sort(pos)
    at = np.searchsorted(low, pos - margin, "right")
    active, tail = len(neg) - at, np.append(np.cumsum(low[::-1])[::-1], 0.0)
    loss = float((active * (margin - pos) + tail[at]).sum()) / (len(pos) * len(neg))
    return loss, active / len(neg), np.searchsorted(high, neg + margin, "left") / len(pos)


class BiEncoder:
    """Query and document through towers of their own; their cosine, a slope and an offset."""

    def __init__(self, dim: int, hidden: int = 64, out: int = 32, seed: int = 42):
        self.q, self.d = MLP([dim, hidden, out], seed), MLP([dim, hidden, out], seed + 1)
        self.affine = np.array([4.0, 0.0])

    def cosine(self, q: np.ndarray, emb: np.ndarray, keep: list | None = None) -> np.ndarray:
        kq, kd = ([], []) if keep is not None else (None, None)
        a, b = self.q.forward(q[None, :], kq), self.d.forward(emb, kd)
        na, nb = np.linalg.norm(a) + 1e-9, np.linalg.norm(b, axis=1) + 1e-9
        cos = (b @ a[0]) / (na * nb)
        if keep is not None:
            keep += [kq, kd, a, b, na, nb, cos]
        return cos

    def prob(self, q, emb, toks=None) -> np.ndarray:
        return sigmoid(self.affine[0] * self.cosine(q, emb) + self.affine[1])

    def _pull(self, keep: list, g: np.ndarray) -> list[np.ndarray]:
        kq, kd, a, b, na, nb, cos = keep
        ga = (g[:, None] * (b / nb[:, None] / na - cos[:, None] * a / na**2)).sum(axis=0, keepdims=True)
        gb = g[:, None] * (a / na / nb[:, None] - (cos / nb**2)[:, None] * b)
        return [*self.q.backward(kq, ga)[0], *self.d.backward(kd, gb)[0]]

    def contrast(self, q, emb, y, epochs: int, lr: float, stage: int) -> list[float]:
        """One stage: 1 pulls each document to or from the query, 2 separates all pairs by a margin, 3 only hard ones."""
        opt, losses = Adam([*self.q.params, *self.d.params], lr), []
        for _ in range(epochs):
            keep: list = []
            cos = self.cosine(q, emb, keep)
            g = np.zeros(len(y))
            pos, neg = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
            if stage == 1 or not len(pos) or not len(neg):
                p = sigmoid(4 * cos)
                loss, g = bce(p, y), 4 * (p - y) / len(y)
            else:
                if stage == 3:
                    pos, neg = pos[np.argsort(cos[pos])[: max(1, len(pos) // 2)]], neg[np.argsort(-cos[neg])[: max(1, len(neg) // 2)]]
                loss, of_pos, of_neg = pair_hinge(cos[pos], cos[neg], 0.4)
                g[pos], g[neg] = -of_pos / len(pos), of_neg / len(neg)
            losses.append(loss)
            opt.step(self._pull(keep, g))
        return losses

    def calibrate(self, q, emb, target, steps: int = 200) -> None:
        """Slope and offset that turn cosines into probabilities."""
        cos, opt = self.cosine(q, emb), Adam([self.affine], 0.05)
        for _ in range(steps):
            g = (sigmoid(self.affine[0] * cos + self.affine[1]) - target) / len(cos)
            opt.step([np.array([float((g * cos).sum()), float(g.sum())])])

    def soft(self, q, emb, target, epochs: int, lr: float) -> None:
        opt = Adam([*self.q.params, *self.d.params, self.affine], lr)
        for _ in range(epochs):
            keep: list = []
            cos = self.cosine(q, emb, keep)
            g = (sigmoid(self.affine[0] * cos + self.affine[1]) - target) / len(cos)
            opt.step([*self._pull(keep, g * self.affine[0]), np.array([float((g * cos).sum()), float(g.sum())])])

    def count(self) -> int:
        return self.q.count() + self.d.count() + 2


def fit_scorer(model, q, emb, toks, target, epochs: int, cfg: Config, seed: int, lr: float | None = None) -> list[float]:
    """Minibatch training of a joint or late scorer on cross-entropy; losses by epoch."""
    rng, opt, losses = np.random.default_rng(seed), Adam(model.params, lr or cfg.lr), []
    for _ in range(epochs):
        order = rng.permutation(len(target))
        for k in range(0, len(order), cfg.batch):
            i = order[k : k + cfg.batch]
            opt.step(model.grad(q, emb[i], [toks[j] for j in i], target[i]))
        losses.append(bce(model.prob(q, emb, toks), target))
    return losses


def fit_contrastive(model, q, emb, toks, y, epochs: int, cfg: Config) -> None:
    """Contrastive training of a joint or late scorer: its log-odds of yes documents above those of no documents."""
    opt, pos, neg = Adam(model.params, cfg.lr), np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(pos) or not len(neg):
        fit_scorer(model, q, emb, toks, y.astype(float), epochs, cfg, cfg.seed)
        return
    for _ in range(epochs):
        p = np.clip(model.prob(q, emb, toks), 1e-6, 1 - 1e-6)
        z = np.log(p / (1 - p))
        _, of_pos, of_neg = pair_hinge(z[pos], z[neg], 2.0)
        gz = np.zeros(len(y))
        gz[pos], gz[neg] = -of_pos / len(pos), of_neg / len(neg)
        target, parts = p - gz * len(y), range(0, len(y), ROWS)
        by_part = [(model.grad(q, emb[k : k + ROWS], toks[k : k + ROWS], target[k : k + ROWS]), len(y[k : k + ROWS]) / len(y)) for k in parts]
        opt.step([sum(g[i] * share for g, share in by_part) for i in range(len(model.params))])
