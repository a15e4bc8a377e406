"""All options of the adaptive selector in one place."""

from __future__ import annotations

import math
from dataclasses import dataclass

CHOICES = {
    "sim_mode": ("shift", "clip", "raw"), "universe": ("train", "pool", "graph", "sample"), "search": ("exact", "hashed"), "schedule": ("constant", "ramp"),
    "importance_rule": ("warped", "largest", "smallest", "raw"), "balance": ("sum", "mean"), "probe_from": ("last_subset", "trained"), "decay": ("recent", "as_printed"),
    "blend": ("half", "energy"), "anchors_from": ("recal", "recal+recent", "all"), "update_policy": ("adaptive", "always", "never", "frozen_subset", "full"), "start": ("initial", "warm"),
}


@dataclass(frozen=True)
class SelectorConfig:
    """Fixed values of the reference: k, decay_rate, bandwidth, affinity_scale and momentum. All others are ours."""

    k: int = 10
    decay_rate: float = 0.99
    bandwidth: float | str = 100.0
    affinity_scale: float = 0.1
    momentum: float = 0.5

    budget_frac: float = 0.10  # of the pool
    pool_frac: float = 0.4  # of the corpus: the share of an epoch that an interval stands for
    pool_size: int | None = None  # instead of the share
    interval_steps: int | None = None  # by default one pass over the picks
    intervals: int = 3
    batch: int | None = None  # rows of a step; None takes all picks
    schedule: str = "constant"  # constant | ramp: up over the first 3 % of the steps, then down to 0
    lam: float = 0.5
    sim_mode: str = "shift"  # shift | clip | raw
    universe: str = "train"  # train | pool | graph | sample
    universe_sample: int = 1000
    search: str = "exact"  # exact | hashed: calibrated to a recall of neighbours
    recall: float = 0.95
    C: float = 10.0
    q: float = 1.0
    r: float = 0.5
    temperature: float = 1.0
    importance_rule: str = "warped"  # warped | largest | smallest | raw
    balance: str = "sum"  # sum | mean
    delta: float = 0.1
    delta_h: float = 0.01
    probe_size: int = 20
    probe_from: str = "last_subset"  # last_subset | trained
    decay: str = "recent"  # recent | as_printed
    affinity_min: float = 0.5
    blend: str = "half"  # half | energy
    anchors_from: str = "recal"  # recal | recal+recent | all
    recompute_budget: int = 40
    min_staleness: int = 1
    update_policy: str = "adaptive"  # adaptive | always | never | frozen_subset | full
    start: str = "initial"  # initial | warm
    warm_frac: float = 0.10
    learning_rate: float = 200.0
    engine: str = "exact"
    seed: int = 42

    def __post_init__(self) -> None:
        if self.C <= 2:
            raise ValueError("C must exceed 2: else no shape of the warp has its mode inside (0, 1)")
        if self.temperature < 0:
            raise ValueError("the temperature cannot be negative")
        for name, known in CHOICES.items():
            if getattr(self, name) not in known:
                raise ValueError(f"{name} is one of {', '.join(known)}")

    def sizes(self, rows: int) -> tuple[int, int]:
        """Rows of the pool and of the budget, which follow the corpus."""
        pool = min(rows, self.pool_size if self.pool_size is not None else max(1, round(self.pool_frac * rows)))
        return pool, max(1, round(self.budget_frac * pool))

    def steps(self, budget: int) -> int:
        """Steps of an interval."""
        return self.interval_steps or (math.ceil(budget / self.batch) if self.batch else 1)
