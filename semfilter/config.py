"""Every parameter of the methods, with its default."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Config:
    """Parameters of a filter run; ``scaled`` fits the sampling floors to a small corpus."""

    alpha: float = 0.9
    k_initial: int = 4
    vote_frac: float = 0.005
    vote_floor: int = 100
    rho: float | None = None  # None: the target accuracy itself
    phase1_frac: float = 0.07
    train_frac: float = 0.07
    cal_frac: float = 0.05
    train_cap: int | None = None  # absolute caps keep label counts payable on very large corpora
    cal_cap: int | None = None
    ranges: int = 20
    blend: float = 0.06
    delta: float = 0.05
    n_candidates: int = 200
    hist_ranges: int = 64
    smooth_c: float = 1.0
    epochs_joint: int = 60
    epochs_late: int = 15
    epochs_head: int = 120
    coverage_weight: float = 0.35
    dual_init: float = 0.01
    dual_lr: float = 0.5
    dual_max: float = 10.0
    emb_dim: int = 128
    tok_dim: int = 64
    late_dim: int = 16
    joint_hidden: int = 64
    head_hidden: tuple[int, int] = (32, 32)
    lr: float = 1e-3
    batch: int = 64
    strata: int = 5
    seed: int = 42
    label_mode: str = "argmax"
    pool_scope: str = "unlabeled"
    binning: str = "per_threshold"
    budget_check: str = "cluster"
    pool_parent_labels: bool = False
    split_cal: bool = False
    max_rounds: int = 12
    extra: dict = field(default_factory=dict, compare=False)

    def scaled(self, n: int) -> Config:
        """The profile for small corpora: the vote floor is at most one percent of the documents."""
        return replace(self, vote_floor=min(self.vote_floor, max(1, math.ceil(0.01 * n))))

    def vote_size(self, n: int) -> int:
        """Documents sampled from each cluster."""
        return max(math.ceil(round(self.vote_frac * n, 9)), self.vote_floor)

    def agreement(self) -> float:
        return self.alpha if self.rho is None else self.rho
